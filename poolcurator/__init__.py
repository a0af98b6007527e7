"""Request-conditioned selection of training data from instruction pools, on Spark."""
