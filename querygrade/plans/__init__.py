"""plans of querygrade."""
