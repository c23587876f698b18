"""Measures and functions over ranks, runs and graphs."""
