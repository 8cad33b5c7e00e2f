"""Patterns, their formulas and their text form."""
