"""Structured streams over events: append under a frozen model, windows, late rows, keyed counts."""
