"""Live reporting with Structured Streaming."""
