"""Contrast patterns on Spark: what tells the rows of one class from all others."""
