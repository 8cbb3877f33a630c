"""Column functions and the registered SQL functions that the operators use."""
