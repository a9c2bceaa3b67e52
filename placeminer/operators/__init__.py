"""Methods over logs and places."""
