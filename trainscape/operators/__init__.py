"""Relational and training operators over DataFrames."""
