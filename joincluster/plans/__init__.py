"""Feature queries, their join trees, and the aggregate-before-join plans over them."""
