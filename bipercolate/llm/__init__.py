"""Operators for training-data pipelines; nothing outside this subpackage depends on them."""
