"""Warm-start registry: one object per Python worker process, kept over tasks.

``REGISTRY.get(factory, *args, **kw)`` builds an object at first use and returns
the same one while the factory and its arguments stay the same.  At most one
object is held: another key destroys the old object before the new one is built.
"""

from __future__ import annotations

import hashlib
import os
import pickle
import time
from collections.abc import Callable
from typing import Any


class Registry:
    def __init__(self) -> None:
        self.key: str | None = None
        self.held: Any = None
        self.loads = 0
        self.hits = 0
        self.seconds = 0.0

    def get(self, factory: Callable, *args: Any, **kw: Any) -> Any:
        key = hashlib.md5(pickle.dumps((factory.__module__, factory.__qualname__, args, sorted(kw.items())))).hexdigest()
        if key == self.key:
            self.hits += 1
            return self.held
        self.drop()
        began = time.perf_counter()
        self.held = factory(*args, **kw)
        self.key = key
        self.loads += 1
        self.seconds += time.perf_counter() - began
        return self.held

    def drop(self) -> None:
        close = getattr(self.held, "close", None)
        self.key = self.held = None
        if close:
            close()

    def trace(self) -> tuple[int, int, int, float]:
        """(process, loads, hits, seconds spent loading)."""
        return os.getpid(), self.loads, self.hits, self.seconds


REGISTRY = Registry()
