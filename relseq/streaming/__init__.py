"""Sequences from event streams."""
