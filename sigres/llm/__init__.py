"""Corpus operators for preparing training data; nothing else in the library imports this package."""
