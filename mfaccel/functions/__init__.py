"""Column functions: vector algebra and hashed starting points."""
