"""Event logs from tables and files."""
