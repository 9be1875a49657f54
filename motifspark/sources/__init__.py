"""Event logs out of tables and files, and sinks."""
