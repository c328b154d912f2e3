"""Choice of strategies and rewrites of plans."""
