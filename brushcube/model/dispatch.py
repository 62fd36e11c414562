"""Throttled dispatch: one event in flight, a newer one replaces the one that waits."""

from __future__ import annotations

import threading
from collections.abc import Callable
from concurrent.futures import Future, wait


class Dispatcher:
    """``handler(event)`` returns futures; the next event starts when all of them are done, failed or not."""

    def __init__(self, handler: Callable[[object], list[Future]]):
        self._handler = handler
        self._lock = threading.Condition()
        self._pending: list = []
        self._busy = False
        self.dispatched = self.dropped = self.failed = 0
        self._closed = False
        self._thread = threading.Thread(target=self._drain, daemon=True)
        self._thread.start()

    def send(self, event) -> None:
        with self._lock:
            if self._pending:
                self.dropped += 1
            self._pending[:] = [event]
            self._lock.notify_all()

    def _drain(self) -> None:
        while True:
            with self._lock:
                self._lock.wait_for(lambda: self._pending or self._closed)
                if self._closed and not self._pending:
                    return
                event, self._busy = self._pending.pop(), True
            try:
                futures = self._handler(event) or []
                wait(futures)
                self.failed += sum(f.exception() is not None for f in futures)
            except Exception:  # a failing handler must free the slot
                self.failed += 1
            with self._lock:
                self.dispatched += 1
                self._busy = False
                self._lock.notify_all()

    def drain(self, timeout: float | None = None) -> bool:
        """Wait until nothing is pending or in flight."""
        with self._lock:
            return self._lock.wait_for(lambda: not self._pending and not self._busy, timeout)

    def close(self) -> None:
        with self._lock:
            self._closed = True
            self._lock.notify_all()

    def stats(self) -> dict[str, int]:
        return {"dispatched": self.dispatched, "dropped": self.dropped, "failed": self.failed}
