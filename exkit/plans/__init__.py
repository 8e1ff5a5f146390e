"""Layouts, partitioners, control plane, cost and measures."""
