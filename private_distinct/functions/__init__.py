"""Scalar functions: keyed hashes and privacy parameters."""
