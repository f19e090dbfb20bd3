"""Live operation over Structured Streaming."""
