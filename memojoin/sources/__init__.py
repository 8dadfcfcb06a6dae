"""Relations from the given tables and from files; sinks."""
