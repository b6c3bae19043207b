"""PageRank, components, traversal, triangles and related block programs."""
