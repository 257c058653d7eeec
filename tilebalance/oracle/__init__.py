"""DuckDB text that states each query again, from the definitions alone."""
