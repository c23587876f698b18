"""Keeping graphs and ranks up to date from streams."""
