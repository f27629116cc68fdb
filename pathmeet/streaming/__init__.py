"""Structured Streaming: request streams against an index, windows, and edge arrivals."""
