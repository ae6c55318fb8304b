"""Incremental folds and windows over streams."""
