"""Structured Streaming maintenance of id lists."""
