"""Encoding, tables, scans, top-k and products over DataFrames."""
