"""evenbox sources."""
