"""Inputs and outputs: tables, files, streams, source-code parsers and the corpora made of the given tables."""
