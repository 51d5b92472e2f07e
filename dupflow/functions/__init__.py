"""Column functions: geometry, qualities, flag bits, bins."""
