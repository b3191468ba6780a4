"""Block-parallel sparse matrix factorisation on Spark, with the operators around it."""
