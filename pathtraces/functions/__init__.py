"""Pure functions: columns and numbers."""
