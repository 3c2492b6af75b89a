"""Online embedding with Structured Streaming."""
