"""Training-data operators. Nothing outside this subpackage imports it; remove it and the rest still works."""
