"""The merge phase: concatenation, principal components, unaligned mean, Procrustes consensus, and extras."""
