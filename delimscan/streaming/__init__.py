"""Streams of byte slices and event-time queries on what is parsed from them."""
