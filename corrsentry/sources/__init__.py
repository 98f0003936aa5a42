"""Readers and sinks, batch and streaming."""
