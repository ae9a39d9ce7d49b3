"""Codes, dictionaries, row and column orders, index building, codecs, aggregation, queries, measures."""
