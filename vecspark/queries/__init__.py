"""Registered queries by family, and the SQL that DuckDB runs beside them."""
