"""Expressions, interval rules and geometry."""
