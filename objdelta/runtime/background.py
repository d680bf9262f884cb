"""Background saving: one save in flight, locks on what it saves, and a log of how long executions waited."""

from __future__ import annotations

import threading
import time
from concurrent.futures import Future


class ScopeLocks:
    """One lock guards the set of names being saved; access to such a name waits, others pass."""

    def __init__(self, mode: str = "scope"):
        self.mode, self._busy, self._changed = mode, set(), threading.Condition()

    def hold(self, names: set[str]) -> None:
        with self._changed:
            self._busy |= set(names)

    def release(self) -> None:
        with self._changed:
            self._busy.clear()
            self._changed.notify_all()

    def access(self, name: str, read_only: bool = False) -> float:
        """Seconds waited for a name; none for code known to be read-only."""
        began = time.perf_counter()
        with self._changed:
            while not read_only and (name in self._busy or (self.mode == "namespace" and self._busy)):
                self._changed.wait()
        return time.perf_counter() - began


class BackgroundSaver:
    """submit() returns at once; a second request first joins the running one, so states stay in order."""

    def __init__(self, locks: ScopeLocks | None = None):
        self.locks, self._running = locks or ScopeLocks(), None

    def submit(self, save, names: set[str]) -> Future:
        self.join()
        done: Future = Future()
        self.locks.hold(names)

        def run():
            try:
                done.set_result(save())
            except BaseException as e:  # handed to whoever joins
                done.set_exception(e)
            finally:
                self.locks.release()

        thread = threading.Thread(target=run, daemon=True)
        self._running = (thread, done)
        thread.start()
        return done

    def join(self):
        if self._running is None:
            return None
        thread, done = self._running
        thread.join()
        self._running = None
        return done.result()


class LatencyLog:
    """Rows (step, phase, seconds) of one session."""

    def __init__(self):
        self.rows: list[tuple[int, str, float]] = []

    def timed(self, step: int, phase: str, run):
        began = time.perf_counter()
        try:
            return run()
        finally:
            self.rows.append((step, phase, time.perf_counter() - began))

    def frame(self, spark):
        return spark.createDataFrame(self.rows, "step int, phase string, seconds double")
