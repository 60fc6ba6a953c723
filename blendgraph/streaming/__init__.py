"""Counts from streams of events."""

from .sessions import CountSink, WindowTail, session_walks, stream_pairs, window_counts

__all__ = ["CountSink", "WindowTail", "session_walks", "stream_pairs", "window_counts"]
