"""Structured Streaming: factors that follow an event stream."""
