"""Structured Streaming: profiles and codes from event streams."""
