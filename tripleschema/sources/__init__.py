"""Sources of the schema-evolution engine."""
