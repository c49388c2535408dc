"""Building when data outgrow a worker: overlapping clusters, local indexes, ordered merging."""
