"""Spark-native scoring, curation, selection and analysis of SQL-generating rollouts."""
