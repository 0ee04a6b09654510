"""The query catalogue of the record-linkage engine and its DuckDB twins."""
