"""Streams of fork requests and of edges."""
