"""Registered queries and workloads."""
