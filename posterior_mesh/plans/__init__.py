"""Looking at plans."""
