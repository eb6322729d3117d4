"""Tables and stored sketch states."""
