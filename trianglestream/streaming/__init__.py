"""Structured Streaming form of the estimators."""
