"""The whole chain and its cost measures."""
