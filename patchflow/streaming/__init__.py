"""Structured Streaming: event source with watermark, stateful gate, windowed counts."""
