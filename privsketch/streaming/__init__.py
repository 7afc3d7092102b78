"""Structured Streaming forms of collection, capping and discovery."""
