"""Rotation-based vector quantization on Spark DataFrames."""
