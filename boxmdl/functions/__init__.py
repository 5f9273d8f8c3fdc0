"""Scalar functions: code lengths as Python functions and as Spark columns, and their SQL forms."""
