"""Spark operators: summaries of strings, learners, validation, measures."""
