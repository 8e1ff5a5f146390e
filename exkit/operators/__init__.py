"""Relational operators and the remedies for skew and stragglers."""
