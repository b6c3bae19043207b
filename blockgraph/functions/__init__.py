"""Column functions: block orders, hashes, sorted-array intersections."""
