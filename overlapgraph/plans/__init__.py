"""Plan choices, fixtures, and the catalogue of queries with their SQL."""
