"""Operators on tensors and tables."""
