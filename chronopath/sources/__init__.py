"""Graphs out of tables, and readers and writers for edges."""
