"""Bucket-averaged local clustering and closure coefficients, as Spark DataFrame plans."""
