"""Choosing how to run a search, and saying why."""
