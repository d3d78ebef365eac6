"""Operators for preparing language-model training data, each a function over DataFrames.

Nothing else in the library imports this subpackage.
"""
