"""evenbox cases."""
