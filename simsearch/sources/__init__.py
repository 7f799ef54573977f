"""Where strings and queries come from, and where results go."""
