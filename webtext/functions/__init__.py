"""Pure functions on one page, block, table or text, and column expressions."""
