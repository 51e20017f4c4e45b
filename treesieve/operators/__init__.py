"""Trees, traversals and joins."""
