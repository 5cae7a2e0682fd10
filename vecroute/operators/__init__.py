"""The relational operators around the engine, each with its DuckDB twin."""
