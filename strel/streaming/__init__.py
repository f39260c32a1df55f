"""Live versions of the methods on streams of events."""
