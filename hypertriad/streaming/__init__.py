"""Windowed edges and incremental triads over streams."""
