"""Streams: windows over events, and references that arrive in batches."""
