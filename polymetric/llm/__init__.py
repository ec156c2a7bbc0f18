"""Operators for training-data pipelines. Nothing else in the package imports them."""
