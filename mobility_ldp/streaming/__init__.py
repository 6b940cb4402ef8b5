"""Structured Streaming: sessions, densities, continuous collection."""
