"""Hypergraphs from tables, text, lists and stored files."""
