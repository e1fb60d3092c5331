"""Registered queries, their SQL oracles, and physical choices."""
