"""Operators on histories, stripes and examples."""
