"""streaming of querygrade."""
