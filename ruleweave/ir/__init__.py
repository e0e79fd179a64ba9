"""Intermediate representation: scoped definitions, lowering, and the two ways to a single self-recursion."""
