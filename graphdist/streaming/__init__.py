"""Arriving edges and queries."""
