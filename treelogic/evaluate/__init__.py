"""Evaluation: candidates, two pruning rounds, match graph, enumeration."""
