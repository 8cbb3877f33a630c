"""Communities of large graphs with an unknown number of blocks, as DataFrame plans."""
