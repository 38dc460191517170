"""A Spark engine for matrix factorisation by accelerated alternating least squares."""
