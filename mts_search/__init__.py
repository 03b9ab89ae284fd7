"""Exact similarity search over windows of multichannel time series, as PySpark DataFrames."""
