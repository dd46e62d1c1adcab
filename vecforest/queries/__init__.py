"""What the driver runs: queries by name, and DuckDB SQL for those that SQL can express."""
