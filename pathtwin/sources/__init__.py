"""Readers and writers."""
from pathtwin.sources.io import read_table

__all__ = ["read_table"]
