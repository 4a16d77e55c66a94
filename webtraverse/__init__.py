"""Prioritised traversal querying of linked documents on Spark."""
