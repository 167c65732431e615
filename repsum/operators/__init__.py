"""Compressor, baselines, merges and use cases as DataFrame operators."""
