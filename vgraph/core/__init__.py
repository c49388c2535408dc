"""Schemas, metrics, the portable mix and session helpers."""
