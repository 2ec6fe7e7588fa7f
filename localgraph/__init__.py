"""Local graph clustering and partitioning on Spark."""
