"""Operators of a training-data pipeline over text corpora, self-contained in this subpackage."""
