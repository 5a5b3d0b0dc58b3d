"""Column, table and aggregate functions over dependencies."""
