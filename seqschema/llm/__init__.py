"""Operators for preparing training text: one module each, none needed by the rest of the library."""
