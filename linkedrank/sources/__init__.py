"""Table readers and staged intermediate tables."""

from linkedrank.sources.tables import TABLES, read_table
from linkedrank.sources.staging import drop_staged, reread, shared_folder, staged, staging, together

__all__ = ["TABLES", "drop_staged", "read_table", "reread", "shared_folder", "staged", "staging", "together"]
