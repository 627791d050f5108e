"""Pipelines, experiments and the registered queries."""
