"""Operators of a training-data pipeline for language models.

Each module holds one operator with a general interface; ``queries`` registers the
thin ``opN_<name>`` queries over the given tables. Nothing else in the library
imports this package.
"""
