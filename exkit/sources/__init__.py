"""Readers of merged blocks and of generated records."""
