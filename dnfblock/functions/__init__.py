"""Column functions: indexing functions, phonetic codes, string similarity."""
