"""Vector tables: reading, validating, deriving from other tables, writing."""
