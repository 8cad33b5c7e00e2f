"""The methods that the study compares with, re-expressed for Spark."""
