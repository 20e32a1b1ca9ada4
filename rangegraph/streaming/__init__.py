"""Streams of events and of arriving objects and queries."""
