"""Pattern support over event streams."""
