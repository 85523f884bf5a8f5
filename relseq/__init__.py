"""Frequent patterns in sequences whose events carry taxonomy concepts and are pairwise related."""
