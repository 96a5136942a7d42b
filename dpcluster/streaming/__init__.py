"""Windowed synopses of event streams."""
