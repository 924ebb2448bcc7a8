"""What a Python worker keeps between batches and tasks: one thing at a time, under a key that names its content."""

from __future__ import annotations

import gc
import hashlib
import pickle
from collections.abc import Callable, Iterable

import pyarrow as pa

_held: tuple[str, object] | None = None


def content_id(*parts: object) -> str:
    """Key of what is made from ``parts``: a digest of their pickles."""
    return hashlib.blake2b(pickle.dumps(parts), digest_size=16).hexdigest()


def give_back() -> None:
    """Free memory goes back to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        import ctypes

        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        pass


def held(key: str, make: Callable[[], object]):
    """What the worker holds under ``key``; anything else that it holds is dropped first, and its memory given back."""
    global _held
    if _held is None or _held[0] != key:
        if _held is not None:
            _held = None
            give_back()
        _held = (key, make())
    return _held[1]


class Memo(dict):
    """A dictionary that is emptied, but for what is named, when what it holds passes about ``limit`` bytes, by ``add``'s reckoning."""

    def __init__(self, limit: int):
        super().__init__()
        self.limit, self.used = limit, 0

    def add(self, key: str, value, size: int) -> None:
        self[key] = value
        self.used += size + len(key) + 150

    def add_all(self, keys: list[str], values: list) -> None:
        """`add` of every key with its value, by the value's length."""
        self.update(zip(keys, values, strict=True))
        self.used += sum(map(len, values)) + sum(map(len, keys)) + 150 * len(keys)

    def trim(self, recent: Iterable[str] = ()) -> None:
        """Between batches: of what is too large, only ``recent`` stays, and of that no more than half the limit."""
        if self.used > self.limit:
            stay = [(k, self[k], len(self[k])) for k in dict.fromkeys(recent) if k in self]
            self.clear()
            self.used = 0
            for k, value, size in stay:
                if self.used > self.limit // 2:
                    break
                self.add(k, value, size)
            give_back()
