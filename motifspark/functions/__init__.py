"""Expressions and user-defined functions."""
