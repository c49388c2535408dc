"""k-NN graph initialisation as DataFrame plans over (src, nbrs, seen) lists."""
