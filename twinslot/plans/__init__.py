"""Choice of method and container by cost."""
