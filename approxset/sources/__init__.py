"""Tables and key sets."""
