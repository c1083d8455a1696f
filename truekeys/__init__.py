"""Finds and removes redundancy that surrogate keys hide in relational data, on Spark."""
