"""Costs, traces and leakage of the methods."""
