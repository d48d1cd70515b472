"""Exact suffix arrays over very large collections of strings, as Spark DataFrame plans."""
