"""Streams: new samples against frozen centres, windows over events, and stateful counts."""
