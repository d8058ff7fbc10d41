"""A bounded memory of words and their ids, for encoders that treat words independently."""

from __future__ import annotations

from collections.abc import Callable, Hashable
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: A word that may not be looked up by itself; its text is cut with more care.
UNSAFE = -2


def spread(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each start, as many as its size."""
    ends = np.cumsum(size)
    total = int(ends[-1]) if len(ends) else 0
    kind = np.int32 if total < 2**31 and (not len(start) or int(start.max()) + total < 2**31) else np.int64
    out = np.repeat((start - (ends - size)).astype(kind), size)
    out += np.arange(total, dtype=kind)
    return out


class WordCache:
    """``learn(keys)`` gives ids and sizes of unseen keys. When ``limit`` keys are held, those that were
    met in one batch only are forgotten, and of the rest at most half the limit stays."""

    def __init__(self, learn: Callable[[list[Hashable]], tuple[np.ndarray, np.ndarray]], limit: int):
        self.learn, self.limit, self.shrunk = learn, limit, 0
        self.clear()

    def clear(self) -> None:
        self.place: dict[Hashable, int] = {}
        self.keys: list[Hashable] = []
        self.pool, self.start, self.size, self.met = np.empty(0, np.int32), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int32)

    def shrink(self) -> None:
        self.shrunk += 1
        keep = np.flatnonzero(self.met >= 2)
        if len(keep) > self.limit // 2:
            keep = np.sort(keep[np.argsort(-self.met[keep], kind="stable")[: self.limit // 2]])
        self.pool = self.pool[spread(self.start[keep], self.size[keep])]
        self.size, self.met = self.size[keep], self.met[keep] // 2
        self.start = np.cumsum(self.size) - self.size
        self.keys = [self.keys[k] for k in keep.tolist()]
        self.place = dict(zip(self.keys, range(len(self.keys)), strict=True))

    def places(self, keys: list[Hashable], safe: np.ndarray | None = None) -> np.ndarray:
        """Where each key's ids are; unseen keys are learned together, unsafe ones are marked."""
        place = np.fromiter(map(self.place.get, keys, repeat(-1)), np.int64, len(keys))
        missing = np.flatnonzero(place == -1).tolist()
        if missing:
            known = list(dict.fromkeys([keys[k] for k in (missing if safe is None else np.flatnonzero((place == -1) & safe).tolist())]))
            if len(self.keys) + len(known) > self.limit and self.keys:
                self.shrink()
                return self.places(keys, safe)
            ids, size = self.learn(known) if known else (np.empty(0, np.int32), np.empty(0, np.int64))
            self.place.update(zip(known, range(len(self.keys), len(self.keys) + len(known)), strict=True))
            self.keys += known
            self.start = np.concatenate((self.start, len(self.pool) + np.cumsum(size) - size))
            self.size = np.concatenate((self.size, size))
            self.met = np.concatenate((self.met, np.zeros(len(known), np.int32)))
            self.pool = np.concatenate((self.pool, ids.astype(np.int32)))
            place[missing] = np.fromiter(map(self.place.get, [keys[k] for k in missing], repeat(UNSAFE)), np.int64, len(missing))
        here = np.zeros(len(self.keys), bool)
        here[place[place >= 0]] = True
        self.met += here
        return place

    def encode(self, texts: pa.Array, safe: Callable[[pa.Array], pa.Array], again: Callable[[str], list[Hashable]], first: Callable[[str], Hashable] | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets) of texts, split at blanks and looked up once per distinct word.

        ``safe`` tells which words may be looked up by themselves; ``first`` gives the key of a text's first word, where it differs from the word; ``again`` cuts a
        text anew if it has an unsafe word, into keys that are no plain words.
        """
        lists = pc.split_pattern(texts, " ")
        cuts, words = lists.offsets.to_numpy().astype(np.int64), lists.flatten().dictionary_encode()
        distinct, fit = words.dictionary.to_numpy(zero_copy_only=False).tolist(), safe(words.dictionary).to_numpy(zero_copy_only=False)
        place = self.places(distinct, fit)[words.indices.to_numpy()]
        if first is not None and len(place):
            # plain places stay valid only as long as the cache has not shrunk
            heads = words.indices.to_numpy()[cuts[:-1] - cuts[0]]
            keys = [first(distinct[k]) for k in heads.tolist()]
            before = self.shrunk
            own = self.places(keys, fit[heads])
            if self.shrunk != before:
                return self.encode(texts, safe, again, first)
            place[cuts[:-1] - cuts[0]] = own
        cuts = cuts - cuts[0]
        odd = np.unique(np.searchsorted(cuts[1:], np.flatnonzero(place == UNSAFE), side="right")).tolist()
        if odd:
            before = self.shrunk
            parts = np.split(place, cuts[1:-1])
            for k in odd:
                parts[k] = self.places(again(texts[k].as_py()))
            if self.shrunk != before:
                return self.encode(texts, safe, again, first)
            place, cuts = np.concatenate(parts), np.append(0, np.cumsum([len(p) for p in parts]))
        size = self.size[place]
        return self.pool[spread(self.start[place], size)], np.append(0, np.cumsum(size))[cuts]
