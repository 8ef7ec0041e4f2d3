"""Matrix products and the algorithms built on them."""
