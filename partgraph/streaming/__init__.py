"""Streams of events: queries that, once drained, equal their batch forms."""
