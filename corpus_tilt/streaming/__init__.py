"""Selection over streams."""
