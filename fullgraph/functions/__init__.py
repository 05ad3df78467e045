"""Column functions: vectors, fixed point, the integer mixer."""
