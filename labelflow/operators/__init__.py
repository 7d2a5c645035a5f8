"""Distributed operators: graph tools, propagation, decoding, measures."""
