"""Budgeted approximate aggregation over equi-joins, on DataFrames."""
