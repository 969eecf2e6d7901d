"""Where graphs and windows come from."""
