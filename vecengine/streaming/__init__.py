"""Structured Streaming: drift, encoding on arrival, index maintenance."""
