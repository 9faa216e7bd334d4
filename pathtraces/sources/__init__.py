"""Where readings come from and results go."""
