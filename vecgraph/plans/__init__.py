"""Checks of physical plans and rewrites of range joins."""
