"""Decisions, options, cost and the entry point."""
