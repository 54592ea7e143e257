"""Functions of the schema-evolution engine."""
