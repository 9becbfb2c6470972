"""Column functions: key codes and prefixes, hashes, filter mathematics."""
