"""Operators over rows: relations, cardinalities, evidence, definitions of a dependency, and what one does with it."""
