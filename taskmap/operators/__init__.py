"""Relational operators on task graphs and mappings."""
