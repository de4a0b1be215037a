"""SQL building blocks: DuckDB texts that the queries are held against."""
