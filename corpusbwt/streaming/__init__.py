"""Streaming appends and windows."""
