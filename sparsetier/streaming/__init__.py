"""Structured Streaming: incremental products, windowed counts, joins and state."""
