"""Training plans and recipes."""
