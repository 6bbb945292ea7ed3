"""Streams of events as growing objects."""
