"""Session-level plumbing: shared folders, shipped code, staged tables, size-checked broadcasts."""
