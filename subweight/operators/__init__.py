"""DataFrame operators: sketches, estimators, bounds."""
