"""Loads every module that registers core queries."""

from __future__ import annotations

from . import methods, registry, relational, streams, whole  # noqa: F401


def load():
    """The filled registry."""
    return registry
