"""Folds over rows, repeated by thin drivers."""
