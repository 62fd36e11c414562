"""Results by query: least recently used, bounded by bytes of Arrow data."""

from __future__ import annotations

import threading
from collections import OrderedDict

import pyarrow as pa


class ResultCache:
    def __init__(self, max_bytes: int = 64 << 20):
        self.max_bytes, self.hits, self.misses, self._size = max_bytes, 0, 0, 0
        self._kept: OrderedDict[str, pa.Table] = OrderedDict()
        self._lock = threading.Lock()

    def get(self, key: str) -> pa.Table | None:
        with self._lock:
            if key in self._kept:
                self.hits += 1
                self._kept.move_to_end(key)
                return self._kept[key]
            self.misses += 1
            return None

    def put(self, key: str, value: pa.Table) -> None:
        with self._lock:
            if value.nbytes > self.max_bytes:
                return
            if key in self._kept:
                self._size -= self._kept.pop(key).nbytes
            self._kept[key] = value
            self._size += value.nbytes
            while self._size > self.max_bytes:
                self._size -= self._kept.popitem(last=False)[1].nbytes
