"""Driver-side planning: queries, covers and packings, bounds, box sides and box packing."""
