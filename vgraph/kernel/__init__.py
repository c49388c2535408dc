"""NumPy bodies that run inside one Arrow task, on the rows of one shard."""
