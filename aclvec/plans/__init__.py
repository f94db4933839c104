"""The query catalogue, its SQL and the experiments."""
