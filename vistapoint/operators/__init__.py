"""Operators on tables of fields of view, cells and clusters."""
