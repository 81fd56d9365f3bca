"""Multi-level sorting, splitting and balanced delivery of large tables on Spark."""
