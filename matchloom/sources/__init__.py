"""Graph builders and readers."""
