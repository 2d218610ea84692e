"""Compositions of operators: loops, two-phase search, workloads."""
