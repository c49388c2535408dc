"""Collect, filter, store: one pipeline for five pruning rules."""
