"""stages of the engine."""
