"""tidegraph: graph traversal and ranking as DataFrame plans."""
