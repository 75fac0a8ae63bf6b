"""Relational operators that several methods share."""
