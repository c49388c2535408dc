"""Sources and sinks for vectors, indexes and truth files."""
