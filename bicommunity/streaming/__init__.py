"""The continuous query on Structured Streaming."""
