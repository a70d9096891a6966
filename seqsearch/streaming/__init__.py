"""Structured Streaming: sequences, histograms, index."""
