"""Products and matrices over streams."""
