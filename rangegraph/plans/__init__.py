"""Choice of the way a search is executed."""
