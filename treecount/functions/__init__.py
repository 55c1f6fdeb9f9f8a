"""Colors, color sets and functions for SQL."""
