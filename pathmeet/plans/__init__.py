"""Measures, workloads, and the catalogue of runnable queries with their SQL oracles."""
