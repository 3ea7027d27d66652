"""Streaming forms of top-K and of the bin filter."""
