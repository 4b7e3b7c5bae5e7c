"""Greedy phrase factorization of static and changing strings, as Spark DataFrame operators."""
