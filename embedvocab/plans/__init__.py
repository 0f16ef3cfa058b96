"""Fixtures, end-to-end plans and the queries with their SQL."""
