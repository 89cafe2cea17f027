"""Sources: pages and their tables, grid files, and the corpus of compact tables derived from the given tables."""
