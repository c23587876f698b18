"""Ranking methods, their baselines, and the relational operators around them."""
