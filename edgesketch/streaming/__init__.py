"""Structured Streaming ingestion and replay."""
