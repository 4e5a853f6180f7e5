"""Range expressions, measures and heaps."""
