"""Subgraph-centric graph analytics on PySpark DataFrames."""
