"""Incrementally maintained classification views, and operators for training data, on Spark."""
