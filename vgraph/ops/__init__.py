"""Relational operators around the graph methods: input preparation, metadata predicates, reporting."""
