"""Streaming ingestion of tensor cells."""
