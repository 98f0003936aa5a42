"""Live detection over event streams."""
