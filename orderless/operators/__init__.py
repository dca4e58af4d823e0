"""DataFrame operators: list codecs, indexes, search, relational wrappers."""
