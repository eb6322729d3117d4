"""Sketches, releases and baselines as DataFrame operators."""
