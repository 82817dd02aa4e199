"""The monitor and its companions on Structured Streaming."""
