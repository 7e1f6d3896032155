"""Structured Streaming: incremental nets per shard, any-time queries, windowed summaries."""
