"""Planning: the order of pattern edges, directions and estimates."""
