"""Bounded patterns over streams of edges."""
