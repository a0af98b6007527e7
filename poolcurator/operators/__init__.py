"""Relational and vector operators that the stages and baselines share."""
