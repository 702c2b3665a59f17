"""Queries over the given tables, one for each method, variant, baseline, measure and workload."""
