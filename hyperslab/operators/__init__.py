"""Access paths for box queries."""
