"""Exact repeated-substring removal over suffixes sorted by the deep-shallow method.

A byte goes if a ``length``-byte string that covers it also starts in a document with a smaller id;
strings are judged on the input and never cross documents. Only suffixes that can repeat are sorted:

1. Every window of ``length`` bytes has an anchor, its least hashed ``GRAM``-byte string (the leftmost of
   equals), which depends on the window's bytes alone; equal windows meet at equal anchors. About one
   position in fifteen is an anchor.
2. Tasks send each batch's distinct anchor hashes, by bucket; the buckets reply which ones occur in more
   than one document.
3. Those anchors' contexts (all windows they stand for) go to the buckets once per batch and text: further
   copies in a batch are settled where they are. Buckets sort the window suffixes of each anchor, multikey
   quicksort over 8-byte characters to a shallow depth and blind tries for what still shares a prefix, so
   that equal windows stand together, and reply which windows start in a document with a smaller id.
4. Batches turn the replies into covered bytes.

Rows travel as packed blobs, one per batch and bucket, whose sizes follow the table's (``grid``); texts are
shuffled once, compressed. Nothing is
broadcast and nothing but the table's size in bytes comes to the driver.

Null texts are empty; null ids count as greater than all ids; documents with equal ids are no source for
each other; repeated rows each get a row. The input must be stable: computing it twice must give the same
rows in the same tasks, as table scans do (``materialize`` makes others so).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packflow.llm.common import NULL_ID, grid, id_or_last, sliced, text_bytes

LENGTH, GRAM = 50, 20
SLICE = 1 << 20
HASH_BITS = 48
#: Bytes to which suffixes are sorted by multikey quicksort before blind tries take over.
SHALLOW = 40


def gram_hashes(a: np.ndarray, k: int) -> np.ndarray:
    """A mixed polynomial hash of every k-byte string, composed from those of powers of two."""
    base, mask = 0x9E3779B97F4A7C15, 2**64 - 1
    done, done_k, part, part_k = None, 0, a.astype(np.uint64) + np.uint64(1), 1
    while True:
        if k & part_k:
            if done is None:
                done = part
            else:
                n = len(part) - done_k
                done = done[:n] * np.uint64(pow(base, part_k, mask + 1)) + part[done_k : done_k + n]
            done_k += part_k
        if part_k * 2 > k:
            break
        part = part[:-part_k] * np.uint64(pow(base, part_k, mask + 1)) + part[part_k:]
        part_k *= 2
    h = done[: len(a) - k + 1].copy()
    h ^= h >> np.uint64(31)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(29)
    return h


def spread_hash(h: np.ndarray) -> np.ndarray:
    """48 bits that are even over their range; anchors' own hashes, being minima, crowd at its low end."""
    h = h * np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(32)
    return (h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - HASH_BITS)


def window_anchors(h: np.ndarray, width: int) -> np.ndarray:
    """For each window of ``width`` hashes the place of its least one, the leftmost of equals."""
    value, place, have = h, np.arange(len(h), dtype=np.int32), 1
    while have < width:
        shift = min(have, width - have)
        n = len(value) - shift
        right = value[shift:] < value[:n]
        place = np.where(right, place[shift:], place[:n])
        value = np.where(right, value[shift:], value[:n])
        have += shift
    return place


def anchors(buf: np.ndarray, ends: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """(place, first, last, hash): anchors of documents laid end to end, with the starts of the windows
    that each stands for, and a 48-bit hash. ``ends`` are the documents' ends."""
    found: list[list[np.ndarray]] = [[], [], [], []]
    starts = np.append(0, ends[:-1])
    for low in range(0, max(0, len(buf) - length + 1), SLICE):
        piece = buf[low : low + SLICE + length - 1]
        h = gram_hashes(piece, gram)
        place = window_anchors(h, length - gram + 1)
        n = len(place)
        # a document's last length - 1 starts have no window
        ok = np.ones(n, bool)
        d0, d1 = np.searchsorted(ends, low, side="right"), np.searchsorted(starts, low + n, side="left")
        for s, e in zip(starts[d0:d1].tolist(), ends[d0:d1].tolist(), strict=True):
            ok[max(s, e - length + 1, low) - low : max(0, min(e - low, n))] = False
        at = np.flatnonzero(ok)
        if not len(at):
            continue
        p = place[at]
        new = np.flatnonzero(np.append(True, (p[1:] != p[:-1]) | (np.diff(at) != 1)))
        stop = np.append(new[1:], len(at)) - 1
        for got, x in zip(found, (p[new].astype(np.int64) + low, at[new] + low, at[stop] + low, spread_hash(h[p[new]])), strict=True):
            got.append(x)
    return tuple(np.concatenate(x) if x else np.empty(0, np.uint64 if k == 3 else np.int64) for k, x in enumerate(found))


class BlindTrie:
    """A Patricia trie of equal-length strings: descend by branching bytes alone, then compare once."""

    def __init__(self):
        self.root = None  # a leaf is [string, members]; an inner node is (place, {byte: node})

    def insert(self, s: bytes, member: int) -> None:
        if self.root is None:
            self.root = [s, [member]]
            return
        node = self.root
        while isinstance(node, tuple):
            node = node[1].get(s[node[0]]) or next(iter(node[1].values()))
        if node[0] == s:
            node[1].append(member)
            return
        other = node[0]
        at = next(i for i in range(len(s)) if s[i] != other[i])
        above, node = None, self.root
        while isinstance(node, tuple) and node[0] < at:
            above, node = node, node[1][s[node[0]]]
        leaf = [s, [member]]
        if isinstance(node, tuple) and node[0] == at:
            node[1][s[at]] = leaf
            return
        split = (at, {other[at]: node, s[at]: leaf})
        if above is None:
            self.root = split
        else:
            above[1][s[above[0]]] = split

    def ordered(self):
        """Groups of members with equal strings, in the strings' order."""
        stack = [self.root]
        while stack:
            node = stack.pop()
            if isinstance(node, tuple):
                stack.extend(child for _, child in sorted(node[1].items(), key=lambda x: -x[0]))
            elif node is not None:
                yield node[1]


def words_at(buf: np.ndarray, at: np.ndarray, n: int = 8) -> np.ndarray:
    """``n`` <= 8 bytes from each place as a number that compares as the bytes do."""
    out = np.zeros(len(at), np.uint64)
    for k in range(n):
        out = out << np.uint64(8) | buf[at + k]
    return out


def multikey_quicksort(buf: np.ndarray, at: np.ndarray, order: np.ndarray, fresh: np.ndarray, depth: int) -> None:
    """Sort each group of suffixes by its first ``depth`` bytes, a multiple of 8, in place.

    ``order`` has the suffixes, ``fresh`` marks where groups begin; both are brought up to date. A character
    is eight bytes. In a round every open group is parted by a character of its own into what is less,
    equal and greater; the equal part goes on with the next character, the others with the same one. All
    groups take the round together, as array operations over the elements that are still open.
    """
    if not depth or not len(order):
        return
    view = np.ndarray(len(buf) - 7, ">u8", buf, strides=(1,))
    start = np.flatnonzero(fresh)
    size = np.diff(np.append(start, len(order)))
    start, size = start[size > 1], size[size > 1]
    done = np.zeros(len(start), np.int64)
    while len(start):
        first = np.cumsum(size) - size
        of = np.repeat(np.arange(len(start)), size)
        index = np.arange(len(of)) + (start - first)[of]
        members = order[index]
        key = view[at[members] + done[of]].astype(np.uint64)
        pivot = key[first + size // 2][of]
        side = (key >= pivot).astype(np.int8) + (key > pivot)  # less, equal, greater
        code = 3 * of + side
        count = np.bincount(code, minlength=3 * len(start))
        base = np.cumsum(count) - count
        rank = np.empty(len(of), np.int64)
        for part in range(3):
            here = side == part
            before = np.cumsum(here) - here
            rank[here] = before[here] - before[first][of[here]]
        moved = np.empty_like(members)
        moved[base[code] + rank] = members
        order[index] = moved
        start, size, done = np.repeat(start - first, 3) + base, count, np.repeat(done, 3) + 8 * (np.arange(len(count)) % 3 == 1)
        fresh[start[size > 0]] = True
        open_ones = (size > 1) & (done < depth)
        start, size, done = start[open_ones], size[open_ones], done[open_ones]


def deep_shallow_sort(buf: np.ndarray, at: np.ndarray, depth: int, shallow: int = SHALLOW, known: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(order, group): suffixes from ``at`` by their first ``depth`` bytes, and which of them, in that
    order, are equal. ``buf`` must hold ``depth`` bytes from every place. Suffixes whose ``known`` numbers
    differ are taken to differ, and those of one number stand together."""
    n = len(at)
    known = np.zeros(n, np.int64) if known is None else known
    order = np.argsort(known, kind="stable")
    fresh = np.append(True, known[order][1:] != known[order][:-1])[:n]
    done = min(shallow, depth) // 8 * 8
    multikey_quicksort(buf, at, order, fresh, done)
    group = np.cumsum(fresh) - 1
    if done >= depth or not n:
        return order, group
    # what shares the shallow prefix: equal to the end, or a case for a blind trie
    starts = np.flatnonzero(np.append(True, group[1:] != group[:-1]))
    size = np.diff(np.append(starts, n))
    mixed = np.zeros(len(starts), bool)
    for k in range(done, depth, 8):
        key = words_at(buf, at[order] + k, min(8, depth - k))
        mixed |= np.minimum.reduceat(key, starts) != np.maximum.reduceat(key, starts)
    raw = buf.tobytes() if mixed.any() else b""
    for g in np.flatnonzero(mixed & (size > 1)).tolist():
        low = int(starts[g])
        trie = BlindTrie()
        for m in order[low : low + size[g]].tolist():
            trie.insert(raw[at[m] + done : at[m] + depth], m)
        k = low
        for members in trie.ordered():
            order[k : k + len(members)] = members
            fresh[k] = True
            k += len(members)
    return order, np.cumsum(fresh) - 1


class Batch:
    """Some documents laid end to end."""

    def __init__(self, ids: np.ndarray, sizes: np.ndarray, raw: bytes):
        self.ids, self.sizes, self.raw = ids, sizes, raw
        self.buf = np.frombuffer(raw, np.uint8)
        self.ends = np.cumsum(sizes)

    def pack(self) -> bytes:
        import zstandard

        return zstandard.compress(np.int64(len(self.ids)).tobytes() + self.ids.tobytes() + self.sizes.tobytes() + self.raw, 3)

    @classmethod
    def unpack(cls, blob: bytes) -> Batch:
        import zstandard

        data = zstandard.decompress(blob)
        n = int(np.frombuffer(data, np.int64, 1)[0])
        return cls(np.frombuffer(data, np.int64, n, 8), np.frombuffer(data, np.int64, n, 8 + 8 * n), data[8 + 16 * n :])

    def doc_of(self, place: np.ndarray) -> np.ndarray:
        return self.ids[np.searchsorted(self.ends, place, side="right")]


def bucket_cuts(hashes: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket's hashes begin in a sorted array."""
    bounds = [-(-(b << HASH_BITS) // buckets) for b in range(buckets + 1)]
    return np.searchsorted(hashes, np.array(bounds, np.uint64))


def gathered(batches, batch_bytes: int):
    """(number, Batch) of about ``batch_bytes`` each; the number is the task's and a count."""
    from pyspark import TaskContext

    number, ids, texts, held = TaskContext.get().partitionId() << 32, [], [], 0
    made = lambda: Batch(np.array(ids, np.int64), np.array([len(t) for t in texts], np.int64), b"".join(texts))
    for part in sliced(batches, "text", batch_bytes // 4):
        new = text_bytes(part.column(1))
        ids += part.column(0).to_pylist()
        texts += new
        held += sum(map(len, new))
        if held >= batch_bytes:
            full, ids, texts, held = made(), [], [], 0
            yield number, full
            number += 1
    if ids:
        yield number, made()


def hash_rows(batch: int, b: Batch, buckets: int, length: int) -> pa.RecordBatch:
    """A batch's distinct anchor hashes by bucket, and which have two documents here already."""
    place, _, _, h = anchors(b.buf, b.ends, length)
    doc = b.doc_of(place)
    order = np.lexsort((doc, h))
    h, doc = h[order], doc[order]
    new = np.append(True, h[1:] != h[:-1])[: len(h)]
    first = np.flatnonzero(new)
    u = h[first]
    several = doc[first] != doc[np.append(first[1:], len(h)) - 1] if len(h) else np.empty(0, bool)
    cuts, keys, blobs = bucket_cuts(u, buckets), [], []
    for k in np.flatnonzero(np.diff(cuts)).tolist():
        low, high = cuts[k], cuts[k + 1]
        keys.append(k)
        offset = u[low:high] - np.uint64(-(-(k << HASH_BITS) // buckets))
        blobs.append(np.int64(high - low).tobytes() + np.ascontiguousarray(offset.view(np.uint8).reshape(-1, 8)[:, :6]).tobytes() + np.packbits(several[low:high]).tobytes())
    return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array([batch] * len(keys), pa.int64()), pa.array(blobs, pa.binary())], names=["bucket", "batch", "blob"])


def shared_hashes(table: pa.Table) -> pa.Table:
    """Of one bucket: for each batch, as bits, which of its hashes have more than one document."""
    blobs = table.column("blob").to_pylist()
    hashes, several = [], []
    for x in blobs:
        n = int(np.frombuffer(x, np.int64, 1)[0])
        h = np.zeros((n, 8), np.uint8)
        h[:, :6] = np.frombuffer(x, np.uint8, 6 * n, 8).reshape(n, 6)
        hashes.append(h.view(np.uint64).ravel())
        several.append(np.unpackbits(np.frombuffer(x, np.uint8, offset=8 + 6 * n), count=n).astype(bool))
    sizes = [len(h) for h in hashes]
    h, many = np.concatenate(hashes), np.concatenate(several)
    order = np.argsort(h, kind="stable")
    same = h[order][1:] == h[order][:-1]
    group = np.cumsum(np.append(True, ~same)) - 1
    several_of = np.bincount(group, many[order]) + (np.bincount(group) > 1) > 0
    out = np.empty(len(h), bool)
    out[order] = several_of[group]
    bits = [np.int64(n).tobytes() + np.packbits(x).tobytes() for n, x in zip(sizes, np.split(out, np.cumsum(sizes)[:-1]), strict=True)]
    return pa.table({"batch": table.column("batch"), "bucket": table.column("bucket"), "bits": pa.array(bits, pa.binary())})


def full_mask(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Bits low..high of each."""
    return ((np.int64(1) << (high - low + 1)) - 1) << low


def replies(place: np.ndarray, mask: np.ndarray) -> bytes:
    import zstandard

    return zstandard.compress(place.astype(np.uint32).tobytes() + mask.astype(np.uint32).tobytes(), 1)


def context_rows(batch: int, b: Batch, shared: pa.Table, buckets: int, length: int) -> pa.RecordBatch:
    """Contexts of the shared anchors by bucket; copies in the batch are settled in a row of their own.

    In a context the anchor stands at ``length - GRAM``; bytes outside its windows are zero.
    """
    import zstandard

    place, first, last, h = anchors(b.buf, b.ends, length)
    u = np.unique(h)
    cuts, flag = bucket_cuts(u, buckets), np.zeros(len(u), bool)
    for bucket, bits in zip(shared.column("bucket").to_pylist(), shared.column("bits").to_pylist(), strict=True):
        n = int(np.frombuffer(bits, np.int64, 1)[0])
        if n != cuts[bucket + 1] - cuts[bucket]:
            raise RuntimeError("the input gave other rows when it was read again; materialize it first")
        flag[cuts[bucket] : cuts[bucket + 1]] = np.unpackbits(np.frombuffer(bits, np.uint8, offset=8), count=n)
    keep = flag[np.searchsorted(u, h)] if len(u) else np.zeros(0, bool)
    place, first, last, h = place[keep], first[keep], last[keep], h[keep]
    keys, blobs = [], []
    if len(place):
        reach = length - GRAM
        padded = np.concatenate((np.zeros(reach, np.uint8), b.buf, np.zeros(length, np.uint8)))
        context = np.lib.stride_tricks.sliding_window_view(padded, reach + length)[place].copy()
        low, high = place - last, place - first  # how far before the anchor the windows start
        column = np.arange(reach + length)
        context[(column < (reach - high)[:, None]) | (column >= (reach - low + length)[:, None])] = 0
        doc = b.doc_of(place)
        words = np.ascontiguousarray(context).view(np.uint64).T
        order = np.lexsort((place, doc, low, high, *words))
        place, low, high, h, doc, context = place[order], low[order], high[order], h[order], doc[order], context[order]
        same = (context[1:] == context[:-1]).all(1) & (low[1:] == low[:-1]) & (high[1:] == high[:-1])
        text = np.cumsum(np.append(True, ~same)) - 1
        head = np.flatnonzero(np.append(True, ~same))
        later = doc > doc[head][text]
        if later.any():
            keys.append(buckets + batch % buckets)
            blobs.append(replies(place[later], full_mask(low, high)[later]))
        place, text = place[~later], text[~later]
        by_hash = np.argsort(h[head], kind="stable")
        rank = np.empty(len(head), np.int64)
        rank[by_hash] = np.arange(len(head))
        head, text = head[by_hash], rank[text]
        o = np.argsort(text, kind="stable")
        place, text = place[o], text[o]
        cuts = bucket_cuts(h[head], buckets)
        for k in np.flatnonzero(np.diff(cuts)).tolist():
            c, d = cuts[k], cuts[k + 1]
            e, f = np.searchsorted(text, [c, d])
            own = head[c:d]
            parts = (np.array([d - c, f - e], np.int64), doc[own], low[own].astype(np.uint8), high[own].astype(np.uint8), context[own], (text[e:f] - c).astype(np.uint32), place[e:f].astype(np.uint32))
            keys.append(k)
            blobs.append(zstandard.compress(b"".join(p.tobytes() for p in parts), 3))
    return pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array([batch] * len(keys), pa.int64()), pa.array(blobs, pa.binary())], names=["bucket", "batch", "blob"])


def earlier_windows(context: np.ndarray, low: np.ndarray, high: np.ndarray, doc: np.ndarray, length: int) -> np.ndarray:
    """For each context, as bits by distance before the anchor, which windows start in a smaller document."""
    words = np.ascontiguousarray(context).view(np.uint64).T
    order = np.lexsort((doc, low, high, *words))
    same = (context[order][1:] == context[order][:-1]).all(1) & (low[order][1:] == low[order][:-1]) & (high[order][1:] == high[order][:-1])
    text = np.empty(len(order), np.int64)
    text[order] = np.cumsum(np.append(True, ~same)) - 1
    head = order[np.append(True, ~same)]  # has the text's least document
    sizes = high[head] - low[head] + 1
    of = np.repeat(np.arange(len(head)), sizes)
    before = np.repeat(high[head], sizes) - (np.arange(len(of)) - np.repeat(np.cumsum(sizes) - sizes, sizes))
    wide = context.shape[1]
    buf = np.ascontiguousarray(context[head]).ravel()
    anchor = words_at(buf, np.arange(len(head)) * wide + wide - length)
    # equal windows have equal anchors at equal distances
    known = np.unique(anchor, return_inverse=True)[1][of] * 32 + before
    ranked, group = deep_shallow_sort(buf, of * wide + (wide - length) - before, length, known=known)
    starts = np.flatnonzero(np.append(True, group[1:] != group[:-1]))
    least = np.minimum.reduceat(doc[head][of[ranked]], starts)[group]
    earlier = np.zeros(len(of), bool)
    earlier[ranked] = least < doc[head][of[ranked]]
    bits = np.bincount(of, np.where(earlier, np.int64(1) << before, 0).astype(float), len(head)).astype(np.int64)
    return np.where(doc > doc[head][text], full_mask(low, high), bits[text])


def resolve(table: pa.Table, buckets: int, length: int) -> pa.Table:
    """Of one bucket: which windows go, per batch. Rows above the buckets are settled and pass."""
    import zstandard

    batches, blobs = table.column("batch").to_pylist(), table.column("blob").to_pylist()
    if table.column("bucket")[0].as_py() >= buckets:
        return pa.table({"batch": pa.array(batches, pa.int64()), "blob": pa.array(blobs, pa.binary())})
    wide, parts, marks = 2 * length - GRAM, [], []
    for x in map(zstandard.decompress, blobs):
        n, m = np.frombuffer(x, np.int64, 2).tolist()
        at = 16 + 10 * n
        parts.append((np.frombuffer(x, np.int64, n, 16), np.frombuffer(x, np.uint8, n, 16 + 8 * n), np.frombuffer(x, np.uint8, n, 16 + 9 * n), np.frombuffer(x, np.uint8, n * wide, at).reshape(n, wide)))
        at += n * wide
        marks.append((np.frombuffer(x, np.uint32, m, at), np.frombuffer(x, np.uint32, m, at + 4 * m)))
    doc, low, high, context = (np.concatenate(p) for p in zip(*parts, strict=True))
    mask = earlier_windows(context, low.astype(np.int64), high.astype(np.int64), doc, length)
    out, at = [], 0
    for (text, place), p in zip(marks, parts, strict=True):
        own = mask[at : at + len(p[0])][text]
        out.append(replies(place[own > 0], own[own > 0]) if (own > 0).any() else None)
        at += len(p[0])
    kept = [k for k, x in enumerate(out) if x is not None]
    return pa.table({"batch": pa.array([batches[k] for k in kept], pa.int64()), "blob": pa.array([out[k] for k in kept], pa.binary())})


def removed_bytes(b: Batch, blobs: list[bytes], length: int) -> np.ndarray:
    """Which bytes of a batch are covered by the windows of all replies."""
    import zstandard

    starts = np.zeros(len(b.buf) + length, np.int32)
    for x in map(zstandard.decompress, blobs):
        n = len(x) // 8
        place, mask = np.frombuffer(x, np.uint32, n).astype(np.int64), np.frombuffer(x, np.uint32, n, 4 * n)
        for bit in range(length - GRAM + 1):
            starts[place[mask >> np.uint32(bit) & np.uint32(1) > 0] - bit] = 1
    total = np.cumsum(starts[: len(b.buf)], dtype=np.int32)
    total[length:] -= total[:-length].copy()
    return total > 0


def kept_rows(b: Batch, gone: np.ndarray, with_text: bool):
    """(id, bytes, removed, spans, digest of the rest or the rest) of each document."""
    begin = b.ends - b.sizes
    run = gone & ~np.append(False, gone[:-1])
    run[begin[b.sizes > 0]] = gone[begin[b.sizes > 0]]
    removed, spans = (np.append(0, np.cumsum(x)) for x in (gone, run))
    rest, cut = b.buf[~gone].tobytes(), np.append(0, np.cumsum(~gone))
    for k, (s, e) in enumerate(zip(begin.tolist(), b.ends.tolist(), strict=True)):
        kept = rest[cut[s] : cut[e]]
        yield int(b.ids[k]), e - s, int(removed[e] - removed[s]), int(spans[e] - spans[s]), kept if with_text else hashlib.sha256(kept).hexdigest()


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, with_text: bool = False) -> DataFrame:
    """(id, n_bytes, n_removed, n_spans, kept_sha256, or kept as binary) for every row."""
    if not GRAM + 1 <= length <= GRAM + 31 or (2 * length - GRAM) % 8:
        raise ValueError("the length must leave 1 to 31 places for the anchor, and contexts of whole words")
    size = docs.agg(F.sum(F.octet_length(F.col(text_col).cast("string")))).first()[0] or 0
    batch_bytes, buckets = grid(size)
    narrow = docs.select(id_or_last(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def pack(rows):
        for number, b in gathered(rows, batch_bytes):
            yield pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), pa.array([b.pack()], pa.binary())], names=["batch", "blob"])

    def hashes(rows):
        for number, b in gathered(rows, batch_bytes):
            yield hash_rows(number, b, buckets, length)

    def contexts(key, left, right):
        rows = [context_rows(key[0].as_py(), Batch.unpack(x), right, buckets, length) for x in left.column("blob").to_pylist()]
        return pa.Table.from_batches(rows, rows[0].schema if rows else pa.schema([("bucket", pa.int64()), ("batch", pa.int64()), ("blob", pa.binary())]))

    last = "kept" if with_text else "kept_sha256"
    names = [id_col, "n_bytes", "n_removed", "n_spans", last]
    types = [pa.int64()] * 4 + [pa.binary() if with_text else pa.string()]

    def finish(left, right):
        rows = []
        for x in left.column("blob").to_pylist():
            b = Batch.unpack(x)
            rows += kept_rows(b, removed_bytes(b, right.column("blob").to_pylist(), length), with_text)
        columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
        columns[0] = [None if k == NULL_ID else k for k in columns[0]]
        return pa.table([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=names)

    batches = narrow.mapInArrow(pack, "batch long, blob binary")
    shared = narrow.mapInArrow(hashes, "bucket long, batch long, blob binary").groupBy("bucket").applyInArrow(shared_hashes, "batch long, bucket long, bits binary")
    wanted = batches.groupBy("batch").cogroup(shared.groupBy("batch")).applyInArrow(contexts, "bucket long, batch long, blob binary")
    gone = wanted.groupBy("bucket").applyInArrow(lambda t: resolve(t, buckets, length), "batch long, blob binary")
    kind = "binary" if with_text else "string"
    return batches.groupBy("batch").cogroup(gone.groupBy("batch")).applyInArrow(finish, f"`{id_col}` long, n_bytes long, n_removed long, n_spans long, {last} {kind}")
