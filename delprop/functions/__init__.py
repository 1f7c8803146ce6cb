"""Column functions: portable hash, vectors, linear interpolants, registered SQL functions."""
