"""Graph suites from the given tables, and a text format for graph collections."""
