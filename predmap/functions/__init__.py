"""Numbers: entropy and space, codes, hashes and linear systems."""
