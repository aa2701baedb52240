"""Distributed algebra over compressed integer sets, as PySpark DataFrames."""
