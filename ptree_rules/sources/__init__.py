"""Where relations come from and results go."""
