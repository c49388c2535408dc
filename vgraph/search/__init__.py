"""Graph search: batched best-first search inside shards, routing between them."""

from .beam import batch_search, beam_search, sharded_search

__all__ = ["batch_search", "beam_search", "sharded_search"]
