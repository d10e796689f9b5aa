"""Column functions: fixed-point vectors, distances, bit packing, ranks."""
