"""SQL twins of graph queries for a second engine (DuckDB): builders of query text."""
