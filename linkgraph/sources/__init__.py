"""Table pairs: loading, cutting out of base tables, sinks."""
