"""Corpus building, matching, skeleton mining, refinement, baselines and measures."""
