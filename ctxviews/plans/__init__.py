"""Catalog, sessions, ranked plans and tools."""
