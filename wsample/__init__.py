"""Weighted random sampling over Spark tables and streams."""
