"""Policies, partitionings, routing, indexes, search, updates and measures."""
