"""Corpus operators for training-data pipelines; nothing else in the package imports this subpackage."""
