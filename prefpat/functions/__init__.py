"""Column functions: portable random numbers, bit masks, features, qualities, model."""
