"""The named queries and their DuckDB twins."""
