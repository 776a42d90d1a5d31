"""Ranges, fragments, sketches and Bloom filters as column functions."""
