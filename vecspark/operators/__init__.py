"""Quantizers, indexes, scans, trees, hashing and additive codes."""
