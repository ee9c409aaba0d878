"""Operators over DataFrames: spatial joins, the linker, relational operators."""
