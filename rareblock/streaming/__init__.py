"""Windows over event time and incremental blocking."""
