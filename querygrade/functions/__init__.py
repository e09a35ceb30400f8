"""functions of querygrade."""
