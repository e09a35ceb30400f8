"""operators of querygrade."""
