"""Plan builders and the catalog of queries."""
