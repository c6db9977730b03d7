"""Column functions: geometry, clipping, descriptors, metrics, text formats, SQL registration."""
