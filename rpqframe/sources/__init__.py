"""Graphs: from relational tables, from node and edge files, and a toy graph."""
