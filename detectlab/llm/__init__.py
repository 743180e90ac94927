"""Operators for building language-model training corpora at 100 TB."""
