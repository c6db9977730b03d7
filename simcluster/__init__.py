"""Search for the most self-similar geometry clusters, written for Spark."""
