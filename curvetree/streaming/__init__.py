"""Streams of points against a frozen grid or a saved index."""

from .points import *  # noqa: F403
