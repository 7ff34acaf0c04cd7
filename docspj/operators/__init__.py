"""Operators over documents: segments, summaries, index, retrieval, statistics, execution."""
