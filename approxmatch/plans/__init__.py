"""Choice of plans."""
