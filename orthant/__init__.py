"""Non-negative low-rank factorization of large dense and sparse matrices on Spark."""
