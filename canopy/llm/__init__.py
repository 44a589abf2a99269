"""Operators for preparing training text; nothing else in canopy imports them."""
