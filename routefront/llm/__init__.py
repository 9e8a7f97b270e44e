"""Training-data operators. Nothing outside this subpackage imports it; it imports nothing of the engine."""
