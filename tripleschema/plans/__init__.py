"""Plans of the schema-evolution engine."""
