"""Reading tables and streams, writing and reading filters."""
