"""Standing queries and appends on streams."""
