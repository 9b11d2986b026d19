"""Column functions: hashes, codes, widths."""
