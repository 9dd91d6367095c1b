"""Hash families, the rotation index, ring search and the rival search frameworks."""
