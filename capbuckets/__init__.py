"""Bucketized releases of microdata under per-value caps on inference, on Spark DataFrames."""
