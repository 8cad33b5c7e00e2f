"""Graphs as node and edge tables, and those that the given tables make."""
