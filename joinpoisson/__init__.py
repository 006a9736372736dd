"""Poisson sampling over relational joins on Spark."""
