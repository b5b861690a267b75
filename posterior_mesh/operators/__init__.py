"""DataFrame operators of the three protocols."""
