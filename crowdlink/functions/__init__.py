"""User-defined scalar, aggregate and table functions."""
