"""Plan builders: query, join, experiments."""
