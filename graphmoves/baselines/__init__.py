"""Sequential, partition-local and other contestants."""
