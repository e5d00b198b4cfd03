"""Operation-based versioned data on Spark."""
