"""Structured Streaming monitors of known dependencies."""
