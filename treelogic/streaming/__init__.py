"""Patterns over event streams: windowed label counts, parent-child pairs, growing contours."""
