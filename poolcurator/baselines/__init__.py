"""baselines of the engine."""
