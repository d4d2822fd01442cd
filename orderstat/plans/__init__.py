"""Decisions made on the driver: parameters, gaps, branches, costs."""
