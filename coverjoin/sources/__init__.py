"""Relations from tables, files and constructed families; sinks for results."""
