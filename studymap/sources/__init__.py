"""Corpora built from the given tables, planted evidence, file readers and sinks."""
