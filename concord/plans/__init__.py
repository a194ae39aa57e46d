"""Whole query plans registered with the entry module."""
