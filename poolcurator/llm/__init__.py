"""Training-data hygiene operators for large text pools (nothing else in the library imports this)."""
