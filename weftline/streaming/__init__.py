"""Structured Streaming: event-time features and overlapped submission."""
