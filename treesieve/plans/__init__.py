"""Queries, their lowering to traversals, and the level-by-level execution of these."""
