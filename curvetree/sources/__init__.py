"""Point clouds: derived from tables, read from files, and kept as ordered indexes."""
