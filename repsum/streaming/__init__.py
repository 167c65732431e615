"""Structured Streaming forms of the compressor and its monitors."""
