"""Operators for preparing language-model training data, each a plain function on DataFrames.

Nothing else in the library imports this subpackage.
"""
