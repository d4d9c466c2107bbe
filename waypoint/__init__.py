"""Path queries over graphs derived from tables, on Spark."""
