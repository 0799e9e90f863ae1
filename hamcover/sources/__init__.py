"""Readers and writers."""

from hamcover.sources.tables import load, read_any, spread, write_any

__all__ = ["load", "read_any", "spread", "write_any"]
