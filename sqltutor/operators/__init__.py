"""DataFrame operators of the methods."""
