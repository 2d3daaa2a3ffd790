"""How products are planned."""
