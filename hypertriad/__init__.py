"""Typed-triad analytics on hypergraphs, Spark first."""
