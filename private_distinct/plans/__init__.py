"""Registered workloads and their SQL."""
