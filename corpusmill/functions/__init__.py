"""Pure functions on texts and HTML, and column expressions built from them."""
