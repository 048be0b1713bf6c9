"""Column functions: seeded hashes, signs, levels."""
