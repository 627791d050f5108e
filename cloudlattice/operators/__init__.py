"""Operators on clouds, cell tables and compressed chunks."""
