"""Relational operators that users of the methods need."""
