"""Structured Streaming forms of resampling, symbolising and induction."""
