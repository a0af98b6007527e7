"""target of the engine."""
