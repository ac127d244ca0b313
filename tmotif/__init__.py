"""Temporal motif counting on Spark."""
