"""Index building blocks and query-time operators."""
