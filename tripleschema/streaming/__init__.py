"""Streaming of the schema-evolution engine."""
