"""Request streams: batches of pending queries with Structured Streaming."""
