"""Filters as DataFrame operators."""
