"""Column functions: tag expressions, probabilities, entropy."""
