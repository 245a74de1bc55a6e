"""Workload queries and their reference SQL."""
