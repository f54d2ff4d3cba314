"""Structured Streaming: windows, late data, state, and extraction of arriving pages."""
