"""Structured Streaming operators over the event trace."""
