"""Relational operators and functions around the methods."""
