"""Choice of method and parameters."""
