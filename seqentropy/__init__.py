"""Entropy of symbol sequences at cluster scale, on PySpark DataFrames."""
