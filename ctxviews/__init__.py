"""Reusable lexical, dense and structural views over versioned text collections, on Spark."""
