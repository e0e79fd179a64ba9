"""Scalar functions and relational operators that users of rule programs need around them."""
