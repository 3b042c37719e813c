"""evenbox functions."""
