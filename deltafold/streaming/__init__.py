"""State backends and Structured Streaming runners."""
