"""sources of querygrade."""
