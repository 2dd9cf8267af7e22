"""Distributed discovery of column dependencies on Spark: unique column combinations, functional and order dependencies, denial constraints."""
