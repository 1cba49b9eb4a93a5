"""Small stand-in students."""
