"""Tables in."""
