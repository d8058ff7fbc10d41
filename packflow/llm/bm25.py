"""Benchmark decontamination: a BM25 inverted index of test items searched with block-max WAND.

Every document is cut into overlapping passages, and every passage is a query of its distinct words
against the index. Impacts are divided by the item's score against itself, so one threshold fits items
of any length. A passage is passed over before the search if no item's rarer words in it, with all that
its most widespread words could add, reach the threshold; that bound, as the block bounds in the
search, never loses a hit. Hits are then
verified; one of three is enough:

* the shares of the item's five-word shingles that the passage holds, for its question (all but the
  last sentence) and its answer (the last sentence) apart, both reach ``OVERLAP``;
* some stretch of the passage is the item but for inserted, dropped or replaced words, at most
  ``1 - OVERLAP`` of the item's own number, so that a few edited words sink no short part;
* the question's share alone reaches ``OVERLAP`` and it has ``QUESTION`` words or more: a question
  without its answer is a leak. It is indexed as a piece of its own. A shorter question, or one with
  edited words, needs its answer, as it may well be another question.

Items longer than ``PIECE`` words are indexed in pieces. A test set is searched in blocks of items of about
``BLOCK_BYTES``; one block's items, and the counts of the words in them, come to the driver at a time and are
broadcast as an index, so that what is broadcast at once does not grow with the test set. Word counts, mean
length and passage length are those of the whole test set, counted on the executors: a score does not depend
on the blocks.

Null and empty texts and items match nothing; repeated rows and null ids get results of their own.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packflow.llm.common import materialize, sliced

K1, B = 1.2, 0.75
PIECE, SHINGLE, POSTINGS_PER_BLOCK = 64, 5, 8
THRESHOLD, OVERLAP, SLACK = 0.6, 0.8, 0.3
#: A question of so many words is a leak without its answer.
QUESTION = 8
BLOCK_BYTES = 16 << 20

words_of = re.compile(r"\w+").findall


def shingles(words: list[str]) -> set[tuple[str, ...]]:
    """Five-word shingles; of fewer words, the whole sequence."""
    return {tuple(words[i : i + SHINGLE]) for i in range(max(1, len(words) - SHINGLE + 1))} if words else set()


def question_and_answer(text: str) -> tuple[str, str]:
    """All but the last sentence, and the last one; a single sentence has no answer."""
    ends = [m.end() for m in re.finditer(r"[.?!]\s+|\n+", text.rstrip())]
    return (text[: ends[-1]], text[ends[-1] :]) if ends else (text, "")


def edits(item: list[int], passage: list[int]) -> int:
    """Least number of inserted, dropped or replaced words between the item and any stretch of the
    passage; a column of the distance table is kept as bits of its differences."""
    places: dict[int, int] = defaultdict(int)
    for i, w in enumerate(item):
        places[w] |= 1 << i
    full, top = (1 << len(item)) - 1, len(item) - 1
    up, down, now = full, 0, len(item)
    least = now
    for w in passage:
        same = places.get(w, 0)
        across = ((((same & up) + up) ^ up) | same) & full
        rise, fall = down | (~(across | up) & full), up & across
        now += (rise >> top & 1) - (fall >> top & 1)
        least = min(least, now)
        rise, fall = rise << 1 & full, fall << 1 & full
        same |= down
        up, down = fall | (~(same | rise) & full), rise & same
    return least


def pieces(text: str | None) -> Iterator[tuple[list[str], tuple[set, set], list[str] | None]]:
    """(words, shingles of question and answer, question that is a piece of its own) of an item's pieces."""
    lowered = (text or "").lower()
    words = words_of(lowered)
    for start in range(0, len(words), PIECE):
        if start and len(words) - start < PIECE // 2:
            continue  # a short last piece belongs to the one before
        whole = len(words) <= PIECE + PIECE // 2
        piece = words[start : start + PIECE] if len(words) - start >= PIECE * 3 // 2 else words[start:]
        q, a = question_and_answer(lowered) if whole else (" ".join(piece), "")
        q_words, a_words = words_of(q), words_of(a)
        yield piece, (shingles(q_words), shingles(a_words)), q_words if a_words and len(q_words) >= QUESTION else None


@dataclass
class Statistics:
    """Of a whole test set: pieces, their words in all, the longest, and how many pieces hold a word."""

    n: int = 0
    words: int = 0
    longest: int = 1
    n_with: dict[str, int] = field(default_factory=dict)

    @classmethod
    def of(cls, texts: Iterable[str | None]) -> Statistics:
        out, seen = cls(), Counter()
        for text in texts:
            for piece, _, _ in pieces(text):
                out.n, out.words, out.longest = out.n + 1, out.words + len(piece), max(out.longest, len(piece))
                seen.update(set(piece))
        out.n_with = dict(seen)
        return out


class Index:
    """Postings by term with the maxima of terms and of blocks of postings."""

    def __init__(self, items: list[tuple[int, str]], statistics: Statistics | None = None):
        stats = statistics or Statistics.of(text for _, text in items)
        self.item: list[int] = []
        self.parts: list[tuple[set, set]] = []
        self.words: list[list[str]] = []
        found = [(key, *piece) for key, text in items for piece in pieces(text)]
        questions = [(key, parts, question) for key, _, parts, question in found if question]
        self.alone = [False] * len(found) + [True] * len(questions)
        for key, words, parts in [(key, words, parts) for key, words, parts, _ in found] + [(key, words, parts) for key, parts, words in questions]:
            self.item.append(key)
            self.parts.append(parts)
            self.words.append(words)
        self.longest, mean = stats.longest, stats.words / max(1, stats.n)
        bags = [Counter(words) for words in self.words]
        postings = defaultdict(list)
        for i, bag in enumerate(bags):
            size = sum(bag.values())
            impact = {t: np.log(1 + (stats.n - stats.n_with[t] + 0.5) / (stats.n_with[t] + 0.5)) * f * (K1 + 1) / (f + K1 * (1 - B + B * size / mean)) for t, f in bag.items()}
            own = sum(impact.values())
            for t, w in impact.items():
                postings[t].append((i, float(w / own)))
        self.term = {t: k for k, t in enumerate(postings)}
        self.terms = [[self.term[w] for w in words] for words in self.words]
        self.docs = [[i for i, _ in p] for p in postings.values()]
        self.impacts = [[w for _, w in p] for p in postings.values()]
        cut = POSTINGS_PER_BLOCK
        self.block_max = [[max(w[k : k + cut]) for k in range(0, len(w), cut)] for w in self.impacts]
        self.block_last = [[d[min(k + cut, len(d)) - 1] for k in range(0, len(d), cut)] for d in self.docs]
        self.essential(len(bags))
        self.most = np.array([max(w) for w in self.impacts] + [0.0])  # the last is for words of no item

    def essential(self, pieces: int) -> None:
        """Split the terms: the most widespread are left out as long as no piece gets more than
        ``SLACK`` from them. A hit needs the rest of its score from essential terms."""
        self.slack, left_out = np.zeros(pieces), set()
        for t in sorted(range(len(self.docs)), key=lambda t: -len(self.docs[t])):
            if len(self.docs[t]) > 1 and all(self.slack[d] + w <= SLACK for d, w in zip(self.docs[t], self.impacts[t], strict=True)):
                self.slack[self.docs[t]] += self.impacts[t]
                left_out.add(t)
        counts = [0 if t in left_out else len(d) for t, d in enumerate(self.docs)] + [0]
        self.ptr = np.append(0, np.cumsum(counts))
        keep = [t for t in range(len(self.docs)) if t not in left_out]
        self.flat_doc = np.array([d for t in keep for d in self.docs[t]], np.int64)
        self.flat_impact = np.array([w for t in keep for w in self.impacts[t]])

    def promising(self, ids: np.ndarray, step: int, threshold: float) -> list[int]:
        """Half-passage numbers at which a passage starts that may hold a hit: some piece's essential
        impacts, repeats included, and its slack reach the threshold."""
        low = self.ptr[ids]
        counts = self.ptr[ids + 1] - low
        at = np.flatnonzero(counts)
        if not len(at):
            return [] if self.slack.max() < threshold else list(range(-(-len(ids) // step)))
        counts = counts[at]
        offset = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
        flat = np.repeat(low[at], counts) + offset
        half, piece = np.repeat(at // step, counts), self.flat_doc[flat]
        last = max(0, -(-len(ids) // step) - 2)
        both = np.concatenate((np.minimum(half, last), np.minimum(np.maximum(half - 1, 0), last)))
        key, place = np.unique(both * len(self.slack) + np.concatenate((piece, piece)), return_inverse=True)
        total = np.bincount(place, np.concatenate((self.flat_impact[flat],) * 2))
        return np.unique(key[total + self.slack[key % len(self.slack)] >= threshold - 1e-9] // len(self.slack)).tolist()

    def search(self, terms: set[int], threshold: float) -> list[tuple[int, float]]:
        """(piece, score) of every piece whose score reaches the threshold, by block-max WAND."""
        theta, found = threshold - 1e-9, []
        lists = [[self.docs[t][0], t, 0] for t in terms]  # current piece, term, place
        docs, most, last, top = self.docs, self.most, self.block_last, self.block_max

        def move(cursor: list, target: int) -> None:
            at = bisect_left(docs[cursor[1]], target, cursor[2])
            cursor[2] = at
            cursor[0] = docs[cursor[1]][at] if at < len(docs[cursor[1]]) else -1

        while lists:
            lists.sort()
            bound, pivot = 0.0, -1
            for k, c in enumerate(lists):
                bound += most[c[1]]
                if bound >= theta:
                    pivot = k
                    break
            if pivot < 0:
                break
            piece = lists[pivot][0]
            while pivot + 1 < len(lists) and lists[pivot + 1][0] == piece:
                pivot += 1
            here, bound, until = lists[: pivot + 1], 0.0, None
            for c in here:
                b = bisect_left(last[c[1]], piece)
                if b < len(top[c[1]]):
                    bound += top[c[1]][b]
                    until = last[c[1]][b] if until is None else min(until, last[c[1]][b])
            if bound < theta:  # no piece up to the nearest block end can reach the threshold
                target = max(piece, until if until is not None else piece) + 1
                if pivot + 1 < len(lists):
                    target = min(target, lists[pivot + 1][0])
                target = max(target, piece + 1) if pivot + 1 >= len(lists) or lists[pivot + 1][0] > piece else target
                for c in here:
                    move(c, target)
            elif lists[0][0] == piece:
                score = sum(self.impacts[c[1]][c[2]] for c in here)
                if score >= theta:
                    found.append((piece, score))
                for c in here:
                    move(c, piece + 1)
            else:
                for c in here:
                    if c[0] < piece:
                        move(c, piece)
            lists = [c for c in lists if c[0] >= 0]
        return found

    def exhaustive(self, terms: set[int], threshold: float) -> list[tuple[int, float]]:
        """The same by adding up all postings, for tests."""
        total: dict[int, float] = defaultdict(float)
        for t in terms:
            for d, w in zip(self.docs[t], self.impacts[t], strict=True):
                total[d] += w
        return sorted((d, s) for d, s in total.items() if s >= threshold - 1e-9)

    def leaks(self, text: str, threshold: float = THRESHOLD, overlap: float = OVERLAP) -> dict[int, tuple[float, float, float]]:
        """item -> (score, question overlap, answer overlap) of the items that a text leaks."""
        words = words_of(text.lower())
        if not words or not self.item:
            return {}
        get, none, step = self.term.get, len(self.term), max(8, self.longest)
        ids = np.fromiter(map(get, words, repeat(none)), np.int64, len(words))
        found: dict[int, tuple[float, float, float]] = {}
        for start in (step * k for k in self.promising(ids, step, threshold)):
            terms = set(ids[start : start + 2 * step].tolist())
            terms.discard(none)
            if self.most[list(terms)].sum() < threshold - 1e-9:
                continue
            hits = self.search(terms, threshold)
            if not hits:
                continue
            held = shingles(words[start : start + 2 * step]) if step >= SHINGLE else set()
            passage = None
            for piece, score in hits:
                shares = []
                for part in self.parts[piece]:
                    short = {s for s in part if len(s) < SHINGLE}
                    if short and passage is None:
                        passage = " " + " ".join(words[start : start + 2 * step]) + " "
                    got = len(part & held) + sum(s not in held and " " + " ".join(s) + " " in passage for s in short)
                    shares.append(got / len(part) if part else 1.0)
                if found.get(self.item[piece], (0.0,))[0] >= score:
                    continue
                if self.alone[piece]:
                    held_enough = shares[0] >= overlap
                else:
                    allowed = int((1 - overlap) * len(self.terms[piece]) + 1e-9)
                    held_enough = min(shares) >= overlap or (allowed > 0 and edits(self.terms[piece], ids[start : start + 2 * step].tolist()) <= allowed)
                if held_enough:
                    found[self.item[piece]] = (score, *shares)
        return found


def indexes(items: DataFrame, item_col: str = "item_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES) -> Iterator[Index]:
    """One index for each block of items, with the statistics of all."""
    items = items.select(F.col(item_col).cast("long").alias("k"), F.col(text_col).cast("string").alias("t")).where("length(t) > 0")
    total = items.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    if not total:
        return
    blocks = -(-total // block_bytes)
    items = materialize(items.withColumn("block", F.pmod(F.xxhash64("k", "t"), F.lit(blocks)).cast("int")), "items")

    def count(batches):
        for batch in batches:
            rows = []
            for block, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for piece, _, _ in pieces(text):
                    rows += [(block, None, len(piece)), *((block, w, 1) for w in sorted(set(piece)))]
            kinds = (pa.int32(), pa.string(), pa.int64())
            columns = zip(*rows, strict=True) if rows else [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["block", "word", "n"])

    words = materialize(items.select("block", "t").mapInArrow(count, "block int, word string, n long"), "item-words")
    whole = words.where("word is null").agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("n"), F.lit(0)).alias("words"), F.coalesce(F.max("n"), F.lit(1)).alias("longest")).first()
    n_with = materialize(words.where("word is not null").groupBy("word").agg(F.count(F.lit(1)).alias("n")), "word-counts")
    for b in range(blocks):
        own = n_with.join(words.where((F.col("block") == b) & F.col("word").isNotNull()).select("word").distinct(), "word")
        stats = Statistics(whole.n, whole.words, whole.longest, {r.word: r.n for r in own.collect()})
        yield Index([(r.k, r.t) for r in items.where(F.col("block") == b).orderBy("k", "t").collect()], stats)


def leaked_items(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, overlap: float = OVERLAP) -> DataFrame:
    """(id, item_id, score, question_overlap, answer_overlap): one row per document and leaked item."""
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"`{id_col}` {kind}, item_id long, score double, question_overlap double, answer_overlap double"
    narrow = docs.select(id_col, F.col(text_col).cast("string").alias("__text")).where(F.length("__text") > 0)
    out = None
    for index in indexes(items):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            leaks = shared.value.leaks
            for batch in sliced(batches, "__text", 8 << 20):
                rows = [(key, item, *values) for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) for item, values in sorted(leaks(text, threshold, overlap).items())]
                types = [batch.schema.field(0).type, pa.int64(), pa.float64(), pa.float64(), pa.float64()]
                columns = list(zip(*rows, strict=True)) if rows else [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=[id_col, "item_id", "score", "question_overlap", "answer_overlap"])

        found = narrow.mapInArrow(run, schema)
        out = found if out is None else out.union(found)
    return docs.sparkSession.createDataFrame([], schema) if out is None else out


def drop_leaking(docs: DataFrame, items: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows that leak no item, with all their columns."""
    for index in indexes(items):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            leaks = shared.value.leaks
            for batch in sliced(batches, text_col, 8 << 20):
                yield batch.filter(pa.array([not (t and leaks(t)) for t in batch.column(text_col).to_pylist()], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
