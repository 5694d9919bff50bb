"""Relations read from tables and files."""
