"""Readers of the given tables and of stored views."""
