"""Relational operators around the methods, each with its SQL."""
