"""Products kept up to date over event streams."""
