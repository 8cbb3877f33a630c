"""Where graphs come from and where blocks go."""
