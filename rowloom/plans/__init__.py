"""Registered queries: each method, measure and workload on the given tables, with its SQL twin."""
