"""Relational operators around archives."""
