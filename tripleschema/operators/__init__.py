"""Operators of the schema-evolution engine."""
