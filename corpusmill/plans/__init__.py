"""Tracks, fixtures and the query catalog."""
