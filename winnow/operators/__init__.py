"""Relational operators on documents and scores."""
