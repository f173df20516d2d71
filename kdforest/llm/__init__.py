"""Operators for preparing training text: one module each, all over plain DataFrames.

Nothing else in the library imports this subpackage; it can be removed as a whole.
"""
