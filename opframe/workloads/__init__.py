"""Case studies on the given tables."""
