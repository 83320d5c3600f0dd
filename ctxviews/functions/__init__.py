"""Column expressions shared by all views."""
