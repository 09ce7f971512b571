"""Training plans: the vectorised meta-gradient engine, downstream models, experiments."""
