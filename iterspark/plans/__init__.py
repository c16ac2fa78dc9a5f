"""Workflow graphs, versions, and the planners that decide what to reuse and what to keep."""
