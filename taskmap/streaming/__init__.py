"""Task graphs from streams of events."""
