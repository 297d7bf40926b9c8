"""Compressing growing sequences, and reading them meanwhile."""

from .online import compress_stream, replay, serve

__all__ = ["compress_stream", "replay", "serve"]
