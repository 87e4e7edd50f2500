"""Objects that a Python worker keeps from task to task."""

from __future__ import annotations

from collections.abc import Callable


def kept(key: object, make: Callable):
    """The worker's object of this key, made at its first use.

    The registry is a module of its own, so that it outlives the functions that
    Spark sends anew with each task.
    """
    import sys
    import types

    registry = sys.modules.setdefault("_treesketch_worker", types.ModuleType("_treesketch_worker")).__dict__.setdefault("objects", {})
    if key not in registry:
        registry.clear()  # one at a time: a worker that has gone on to other work needs its memory
        registry[key] = make()
    return registry[key]


def forget() -> None:
    """Free what ``kept`` holds; operators that need none of it call this first."""
    import sys

    module = sys.modules.get("_treesketch_worker")
    if module is not None and module.__dict__.get("objects"):
        module.__dict__["objects"].clear()
