"""Column functions: portable hashing, array algebra, user-defined objects."""
