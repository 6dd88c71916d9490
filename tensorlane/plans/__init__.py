"""Execution lanes: how a compiled pipeline becomes a Spark plan."""
