"""Two-tier, versioned semantic search over changing documents, on Spark."""
