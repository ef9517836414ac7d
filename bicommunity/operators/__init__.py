"""Graph, motif, pruning and community operators."""
