"""Upkeep of index and model by streams, and windowed counts of events."""
