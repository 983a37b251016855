"""Operators for training-data pipelines: near duplicates, filters, archives and tokens.

Nothing else in the package imports this subpackage.
"""
