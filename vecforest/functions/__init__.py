"""Parameters, statistics and column expressions."""
