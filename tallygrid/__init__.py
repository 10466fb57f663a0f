"""Approximate counting with hashed counter grids on Spark, with estimates and intervals drawn from the grids' own errors."""
