"""Operators for large training-text corpora.  Nothing else in the library imports this package."""
