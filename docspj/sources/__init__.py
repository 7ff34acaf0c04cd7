"""Corpora over the given tables, a Python data source, sinks."""
