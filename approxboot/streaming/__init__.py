"""Early answers over streams."""
