"""Where matrices come from: generated ones, and the given tables."""
