"""Structured Streaming operators on call events."""
