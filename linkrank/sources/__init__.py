"""Readers, graph builders over the given tables, and generators."""
