"""Measures of the study: times, sizes, candidates, index and intermediate cells, joins, bytes."""
