"""Policies and profiles: small frozen values passed to operators and models."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class PackPolicy:
    """When a pack closes.

    ``b_min`` closes a pack for efficiency. ``b_max`` bounds it: with ``ceiling="before"`` a unit that
    would pass it closes the pack first, with ``"after"`` the bound is only looked at once the unit is in.
    Partitions over ``b_max`` stay whole (``oversize="own"``) or are cut into units of ``b_max``
    (``"split"``); only ``before`` with ``split`` bounds packs whatever the sizes and their order.
    """

    b_min: int
    b_max: int
    ceiling: str = "before"
    oversize: str = "split"
    unit: str = "texts"
    strict: bool = True

    def __post_init__(self):
        if not 1 <= self.b_min <= self.b_max:
            raise ValueError("thresholds must satisfy 1 <= b_min <= b_max")
        if self.ceiling not in ("before", "after") or self.oversize not in ("own", "split") or self.unit not in ("texts", "bytes"):
            raise ValueError("unknown policy value")
        if self.strict and self.ceiling == "before" and self.b_max < 2 * self.b_min:
            raise ValueError("b_max must be at least twice b_min for the bound on the number of packs")

    @classmethod
    def for_texts(cls, n: int, share: float = 0.01, **more) -> PackPolicy:
        """Thresholds in the usual proportions: b_min a hundredth of all texts, b_max five times that."""
        b_min = max(1, -(-int(n * share * 1_000_000) // 1_000_000))
        return cls(b_min, 5 * b_min, **more)

    def bound(self, n_max: int) -> int:
        """Largest possible pack when the largest partition has ``n_max`` texts."""
        if self.ceiling == "after":
            return self.b_min - 1 + (min(n_max, self.b_max) if self.oversize == "split" else n_max)
        return self.b_max if self.oversize == "split" else max(self.b_max, n_max)


@dataclass(frozen=True)
class EncoderProfile:
    """An encoder: dimension, fixed seconds per call, milliseconds per text on one worker, workers.

    ``call_s`` is waited in every live call: the price of a device call where there is no device. ``batch``
    is what a device takes at once; a call is worked off in such batches.
    """

    name: str
    dim: int = 64
    c_ipc: float = 0.087
    c_enc_ms: float = 0.149
    workers: int = 4
    work: int = 1
    batch: int = 1024
    call_s: float = 0.0
    device_options: dict = field(default_factory=dict, hash=False)
    deterministic_per_text: bool = True


@dataclass(frozen=True)
class StorageProfile:
    """Simulated store: a wait of ``base_ms`` and of the bytes over ``mb_per_s`` (0: no limit)."""

    name: str
    base_ms: float = 0.0
    mb_per_s: float = 0.0
    spike_rate: float = 0.0
    spike_ms: float = 0.0

    def seconds(self, n_bytes: int, parts: int = 1) -> float:
        return parts * self.base_ms / 1000 + (n_bytes / (self.mb_per_s * 1e6) if self.mb_per_s else 0.0)


@dataclass(frozen=True)
class RetryPolicy:
    """Attempts and waits of 1, 2, 4, ... times ``base_seconds``."""

    attempts: int = 3
    base_seconds: float = 1.0


# Profiles of the reported experiments (seconds, milliseconds, workers; batch per device).
SMALL = EncoderProfile("small", 384, 0.087, 0.149, 4)
MID = EncoderProfile("mid", 768, 0.081, 0.215, 2, work=2, batch=512)
SWEEP = EncoderProfile("sweep", 384, 0.067, 0.110, 2)
LARGE = EncoderProfile("large", 1024, 0.087, 0.409, 4, work=4)
PROFILES = {p.name: p for p in (SMALL, MID, SWEEP, LARGE)}
DEVICE_BATCH = {"l4": 1024, "a100": 2048, "l4-mid": 512}
STORES = {
    p.name: p
    for p in (
        StorageProfile("null"), StorageProfile("local", 2.0), StorageProfile("regional", 10.0, 200.0),
        StorageProfile("same_region", 20.0, 200.0), StorageProfile("cross_region", 50.0, 200.0),
    )
}
DOLLARS_PER_HOUR = 7.30
MEAN_TEXT_BYTES = 47
