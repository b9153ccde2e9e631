"""Matrix operations, closures, components and tiles."""
