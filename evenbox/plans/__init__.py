"""evenbox plans."""
