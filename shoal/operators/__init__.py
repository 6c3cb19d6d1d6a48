"""Community detection methods and their steps."""
