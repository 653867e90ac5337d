"""DataFrame operators: windows, matches, relational index tables, segments."""
