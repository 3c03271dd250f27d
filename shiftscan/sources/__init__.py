"""Feeds, metadata and raw messages."""
