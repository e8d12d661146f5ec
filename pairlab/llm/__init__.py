"""Corpus operators for training-data pipelines.  Nothing else in pairlab imports this subpackage."""
