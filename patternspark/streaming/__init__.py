"""Mining over event streams."""
