"""Subgraph matching over streaming multigraphs, planned as DataFrames."""
