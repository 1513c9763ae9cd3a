"""Column functions: cleaning, validation, key parts, phonetic codes."""
