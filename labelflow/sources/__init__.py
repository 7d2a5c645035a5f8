"""Readers, writers, graph builders, seeds."""
