"""Structured Streaming: windowed and stateful sketches."""
