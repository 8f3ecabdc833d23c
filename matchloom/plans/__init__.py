"""Reports on physical plans."""
