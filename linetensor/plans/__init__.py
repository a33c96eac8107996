"""Choices made before execution, and iterative plans."""
