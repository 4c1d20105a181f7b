"""Corpus operators for preparing language-model training data.

Nothing else in the library imports this subpackage; ``registry`` holds its
queries and their SQL.
"""
