"""workloads of the engine."""
