"""Two-tier vector retrieval and context condensation on Spark."""
