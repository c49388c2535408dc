"""Compared builders: incremental insertion, iterated collect-and-prune, two-pass relaxed, divide and conquer, disk flow."""
