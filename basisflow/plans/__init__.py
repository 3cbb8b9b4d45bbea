"""Named queries over the given tables, with their DuckDB twins."""
