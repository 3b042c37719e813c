"""evenbox operators."""
