"""Accuracy, time, cost and graph measures."""
