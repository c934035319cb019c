"""Operators for building language-model training corpora."""
