"""Workflows over the given tables, each with a list of edits."""
