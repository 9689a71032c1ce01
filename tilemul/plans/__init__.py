"""Strategy choice, rewrites and plan checks."""
