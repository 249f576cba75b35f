"""Part of the factorization engine."""
