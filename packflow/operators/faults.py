"""Sinks that fail on purpose, by a hash of the key: for recovery runs and tests."""

from __future__ import annotations

import hashlib


def key_number(key: str | None) -> int:
    """The first eight hex digits of the MD5, as ``sizes.md5_number`` has it."""
    return int(hashlib.md5((key or "").encode()).hexdigest()[:8], 16)


class PoisonedSink:
    """Raises at every key whose number is a multiple of ``every``, as a machine that dies there would."""

    def __init__(self, sink, every: int):
        self.sink, self.every = sink, every

    def path(self, unit) -> str:
        return self.sink.path(unit)

    def __call__(self, unit, matrix) -> str:
        if key_number(unit.key) % self.every == 0:
            raise SystemError(f"lost while writing {unit.key!r}")
        return self.sink(unit, matrix)


class FlakySink:
    """The first ``times`` writes of every key whose number is a multiple of ``every`` fail."""

    def __init__(self, sink, every: int, times: int):
        self.sink, self.every, self.times, self.tries = sink, every, times, {}

    def path(self, unit) -> str:
        return self.sink.path(unit)

    def __call__(self, unit, matrix) -> str:
        at = self.sink.path(unit)
        if key_number(unit.key) % self.every == 0 and self.tries.get(at, 0) < self.times:
            self.tries[at] = self.tries.get(at, 0) + 1
            raise OSError("the store did not answer")
        return self.sink(unit, matrix)
