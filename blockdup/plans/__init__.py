"""Measures, experiments and the registry of named queries."""
