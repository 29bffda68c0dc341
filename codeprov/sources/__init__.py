"""Where code and posts come from."""
