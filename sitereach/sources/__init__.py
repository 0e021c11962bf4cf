"""Tables in and out."""

from .tables import keep, read, store_dir, table, write

__all__ = ["keep", "read", "store_dir", "table", "write"]
