"""Operators on temporal relations."""
