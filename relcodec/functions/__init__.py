"""Scalar functions that codecs are built of, and batch functions for SQL."""
