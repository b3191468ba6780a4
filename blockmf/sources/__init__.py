"""Where ratings come from and where models go."""
