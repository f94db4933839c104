"""Policy changes and query logs as streams."""
