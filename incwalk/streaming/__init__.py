"""Structured Streaming: maintenance of the walk store and windowed arrivals."""
