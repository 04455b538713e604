"""Column functions: geometry, slots, SQL functions."""
