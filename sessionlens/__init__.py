"""Weighted fuzzy clustering of web-usage sessions on Spark, from raw logs to chosen clusters."""
