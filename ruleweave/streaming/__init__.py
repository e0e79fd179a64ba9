"""Streams: windows with watermarks, and insert-only maintenance of recursive relations."""
