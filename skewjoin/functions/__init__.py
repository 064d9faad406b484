"""Key, hash and distribution expressions."""
