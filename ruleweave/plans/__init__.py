"""Logical plans: conjunctions as DataFrames, programs as ordered definitions, keys as plan knowledge."""
