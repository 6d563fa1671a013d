"""Operators for training-data corpora; nothing else in the library imports this subpackage."""
