"""The library inside SQL statements."""
