"""twoview: vector search on compact codes that read both as table indices and as bit strings."""
