"""Column-level building blocks: taxonomies, relations and views of sequences."""
