"""DataFrame operators: grid join, clusters, similarity index, features, sampling, density, labels, budgets."""
