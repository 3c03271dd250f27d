"""Sliding-window state-shift detection on Spark."""
