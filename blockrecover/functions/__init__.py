"""Column functions: checksums and their algebra, byte helpers."""
