"""Coded gradient descent and the table operators around it, for Spark."""
