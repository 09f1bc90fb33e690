"""Relational operators around traversals."""
