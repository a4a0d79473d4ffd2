"""What Python workers remember between tasks.

Spark reuses worker processes, so a tokenizer's memory of chunks serves many tasks; but
it also stays while other operators run. Each operator announces itself, and whatever
another one remembered is dropped.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable

_active: str | None = None
_forget: dict[str, Callable[[], object]] = {}


def remembers(name: str, forget: Callable[[], object]) -> None:
    _forget[name] = forget


def enter(name: str) -> None:
    global _active
    if _active == name:
        return
    _active = name
    dropped = [_forget[other]() for other in _forget if other != name]
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None) if dropped else None
    if trim:
        trim(0)
