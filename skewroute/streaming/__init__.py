"""The same router over Structured Streaming."""
