"""evenbox streaming."""
