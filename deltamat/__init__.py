"""deltamat: products of large, changing sparse matrices on Spark."""
