"""The chain and its summaries over streams."""
