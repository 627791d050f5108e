"""Clouds from tables and files."""
