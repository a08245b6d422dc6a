"""Counts kept current on streams of events."""
