"""Block compression of categorical tables, on Spark."""
