"""Facts that arrive as a stream."""
