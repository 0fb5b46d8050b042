"""Registered queries: workloads, measures and the relational surface, with their SQL."""
