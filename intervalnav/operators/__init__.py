"""Operators on objects, graphs and results."""
