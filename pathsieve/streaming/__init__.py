"""Structured Streaming: edges from events, maintenance of masks, standing queries."""
