"""Operators on training-data tables; nothing else in the library imports this."""
