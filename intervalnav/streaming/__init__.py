"""Streams of objects and standing queries."""
