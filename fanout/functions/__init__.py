"""Parameters, hashes, slots and other column functions."""
