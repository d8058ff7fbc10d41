"""SentencePiece BPE encoding and decoding by vectorised merge rounds.

Words (a run of the space mark and what follows it) merge independently, for no piece holds a mark
after another character; each distinct word of a batch is merged once, all of them at the same time:
flat symbol arrays, the lowest pair rank of every word by a segmented minimum, all leftmost
non-overlapping pairs of that rank merged at once, arrays compacted, until no pair is left.

Merging all of a word's best pairs at once equals the library's one-at-a-time order unless a new
pair would come before the rest; such words merge only their first pair in that round.

Null texts are empty. An empty text has the end id alone. Characters outside the vocabulary become
byte pieces. Rows keep their ids and order; repeated rows give repeated results.
"""

from __future__ import annotations

import functools
import hashlib
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from packflow.llm.common import sliced
from packflow.llm.wordcache import WordCache, spread

MARK = "▁"
NO_RANK = np.int64(2**62)
#: Words that a Python worker remembers.
MAX_WORDS = 250_000


class PieceModel:
    """The tables of one model file, and a memory of words already merged."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.vocab_size()
        pieces = [sp.id_to_piece(i) for i in range(n)]
        special = [sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) for i in range(n)]
        self.byte_ids = np.full(256, -1, np.int64)
        for i in range(n):
            if sp.is_byte(i):
                self.byte_ids[int(pieces[i][3:5], 16)] = i
        if (self.byte_ids < 0).any() or sp.is_unused(n - 1):
            raise ValueError("only BPE models with byte fallback are read")
        for probe in ("  a  b ", "ﬁ１", "a \tb"):
            if sp.normalize(probe).replace(MARK, " ") != " " + probe:
                raise ValueError("only models that leave texts as they are, but for a leading mark, are read")
        self.eos = sp.eos_id()
        normal = {p: i for i, p in enumerate(pieces) if not special[i]}
        if any(MARK in p.lstrip(MARK) for p in normal):
            raise ValueError("a piece holds the space mark after another character")
        symbols = dict(normal)  # and single characters that only longer pieces hold
        for p in normal:
            for c in p:
                symbols.setdefault(c, len(pieces) + len(symbols))
        self.extra = {v: k for k, v in symbols.items() if v >= n}
        order = sorted(normal.values(), key=lambda i: -sp.get_score(i))
        rank = np.full(n, NO_RANK)
        rank[order] = np.unique([-sp.get_score(i) for i in order], return_inverse=True)[1]
        self.tied = np.bincount(rank[[i for p, i in normal.items() if len(p) > 1]]) > 1
        self.width = max(symbols.values()) + 1
        keys, made = [], []
        for p, i in normal.items():
            for k in range(1, len(p)):
                left, right = symbols.get(p[:k]), symbols.get(p[k:])
                if left is not None and right is not None:
                    keys.append(left * self.width + right)
                    made.append(i)
        order2 = np.argsort(np.array(keys, np.int64))
        self.pair_key = np.array(keys, np.int64)[order2]
        self.pair_piece = np.array(made, np.int64)[order2]
        self.pair_rank = rank[self.pair_piece]
        self.of_char = -1 - np.arange(0x110000, dtype=np.int64)  # below 0: outside the tables
        for s, i in symbols.items():
            if len(s) == 1:
                self.of_char[ord(s)] = i
        self.vocab = n
        self.text_of = [b"" if special[i] and not sp.is_byte(i) else bytes((int(p[3:5], 16),)) if sp.is_byte(i) else p.replace(MARK, " ").encode() for i, p in enumerate(pieces)]
        for name, strings in (("decimal", [f"{i} ".encode() for i in range(n)]), ("text", self.text_of)):
            sizes = np.array([len(x) for x in strings], np.int64)
            setattr(self, f"{name}_flat", np.frombuffer(b"".join(strings), np.uint8))
            setattr(self, f"{name}_start", np.cumsum(sizes) - sizes)
            setattr(self, f"{name}_size", sizes)
        self.cache = WordCache(self.learn, MAX_WORDS)

    def look_up(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(rank, piece) of each pair; NO_RANK where the two don't make a piece."""
        key = np.where((left < 0) | (right < 0), -1, left * self.width + right)
        at = np.minimum(np.searchsorted(self.pair_key, key), len(self.pair_key) - 1)
        hit = self.pair_key[at] == key
        return np.where(hit, self.pair_rank[at], NO_RANK), self.pair_piece[at]

    def merge(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets) of non-empty words."""
        codes = np.frombuffer("".join(words).encode("utf-32-le"), np.uint32)
        sym, seg = self.of_char[codes], np.repeat(np.arange(len(words)), [len(w) for w in words])
        done_sym, done_seg = [], []
        same = np.append(seg[1:] == seg[:-1], False)
        rank, piece = self.look_up(sym, np.append(sym[1:], -1))
        rank[~same] = NO_RANK
        while len(sym):
            fresh = np.append(True, seg[1:] != seg[:-1])
            word = np.cumsum(fresh) - 1
            best = np.minimum.reduceat(rank, np.flatnonzero(fresh))[word]
            still = best < NO_RANK
            if not still.all():
                done_sym.append(sym[~still])
                done_seg.append(seg[~still])
            at = np.flatnonzero((rank == best) & still)
            if not len(at):
                break
            if (seg[at[1:]] == seg[at[:-1]]).any():  # of touching pairs, every other one from the left
                fresh = np.append(True, np.diff(at) != 1)
                at = at[(np.arange(len(at)) - np.flatnonzero(fresh)[np.cumsum(fresh) - 1]) % 2 == 0]
                at = at[self.safe(at, sym, seg, piece[at], best[at])]
            sym[at] = piece[at]
            still[at + 1] = False
            sym, seg, rank, piece, now = sym[still], seg[still], rank[still], piece[still], np.cumsum(still)[at] - 1
            now = np.concatenate((now, now[now > 0] - 1))  # only pairs with a merged symbol have changed
            after = np.minimum(now + 1, len(sym) - 1)
            rank[now], piece[now] = self.look_up(sym[now], sym[after])
            rank[now[(seg[now] != seg[after]) | (now == after)]] = NO_RANK
        sym, seg = np.concatenate(done_sym), np.concatenate(done_seg)
        order = np.argsort(seg, kind="stable")
        return self.spell(sym[order], seg[order], len(words))

    def safe(self, at: np.ndarray, sym: np.ndarray, seg: np.ndarray, made: np.ndarray, best: np.ndarray) -> np.ndarray:
        """Which of the chosen pairs may merge in this round: all, or a word's first if order matters."""
        first = np.append(True, seg[at[1:]] != seg[at[:-1]])
        if first.all():
            return first
        after = np.minimum(at + 2, len(sym) - 1)
        right = np.where((at + 2 < len(sym)) & (seg[after] == seg[at]), sym[after], -1)
        before = np.maximum(at - 1, 0)
        left = np.where((at > 0) & (seg[before] == seg[at]), sym[before], -1)
        touching = np.append(False, (np.diff(at) == 2) & ~first[1:])
        left = np.where(touching, made, left)
        sooner = (self.look_up(left, made)[0] < best) | (self.look_up(made, right)[0] < best)
        bad = np.unique(seg[at[sooner | self.tied[best]]])
        return first | ~np.isin(seg[at], bad)

    def spell(self, sym: np.ndarray, seg: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids in place of symbols, byte pieces in place of characters outside the vocabulary."""
        odd = np.flatnonzero((sym < 0) | (sym >= self.vocab))
        if len(odd):
            spelled = [self.byte_ids[list((chr(-1 - s) if s < 0 else self.extra[s]).encode())] for s in sym[odd].tolist()]
            counts = np.ones(len(sym), np.int64)
            counts[odd] = [len(b) for b in spelled]
            ids = np.repeat(sym, counts)
            ids[np.repeat(np.isin(np.arange(len(sym)), odd), counts)] = np.concatenate(spelled)
            sym, seg = ids, np.repeat(seg, counts)
        return sym, np.append(0, np.cumsum(np.bincount(seg, minlength=words)))

    def decode(self, ids) -> str:
        """As the library: control ids vanish, byte pieces join, one leading blank goes."""
        out = b"".join(self.text_of[i] for i in ids).decode("utf-8", "replace")
        return out[1:] if out[:1] == " " else out

    def learn(self, words: list) -> tuple[np.ndarray, np.ndarray]:
        ids, cuts = self.merge([MARK + (w if isinstance(w, str) else w[1]) for w in words])
        return ids, np.diff(cuts)

    @staticmethod
    def plain(words: pa.Array) -> pa.Array:
        """Words that are bounded by single blanks and hold no mark merge as they are."""
        return pc.and_not(pc.greater(pc.binary_length(words), 0), pc.match_substring(words, MARK))

    @staticmethod
    def cut(text: str) -> list:
        """A text's words without their first mark, whatever blanks and marks it has."""
        return [("cut", w[1:]) for w in re.findall(f"{MARK}+[^{MARK}]*", MARK + text.replace(" ", MARK))] if text else []

    def encode(self, texts: pa.Array, add_eos: bool = True) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets) of texts; words not in the cache are merged together first."""
        ids, cuts = self.cache.encode(texts, self.plain, self.cut)
        if add_eos:
            ids = np.insert(ids, cuts[1:], self.eos)
            cuts = cuts + np.arange(len(cuts))
        return ids, cuts

    def decimal_bytes(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids as decimal numbers, each with a blank after it, and where each begins."""
        return self.spell_out(ids, self.decimal_flat, self.decimal_start, self.decimal_size)

    def text_bytes(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids' texts, blanks for marks, control ids empty, and where each begins."""
        return self.spell_out(ids, self.text_flat, self.text_start, self.text_size)

    @staticmethod
    def spell_out(ids, flat, start, size) -> tuple[np.ndarray, np.ndarray]:
        sizes = size[ids]
        return flat[spread(start[ids], sizes)], np.append(0, np.cumsum(sizes))


@functools.cache
def model(path: str) -> PieceModel:
    return PieceModel(path)


def encode_pieces(df: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", add_eos: bool = True) -> DataFrame:
    """(id, ids): the piece ids of each whole text."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches):
        m = model(model_path)
        for batch in sliced(batches, "__text", 2 << 20):
            ids, cuts = m.encode(batch.column(1).fill_null(""), add_eos)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(ids))], names=[id_col, "ids"])

    return df.selectExpr(f"`{id_col}`", f"cast(`{text_col}` as string) as __text").mapInArrow(run, f"`{id_col}` {kind}, ids array<int>")


def decode_pieces(df: DataFrame, model_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text): ids turned back into text; null ids give an empty text."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches):
        m = model(model_path)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([m.decode(ids or ()) for ids in batch.column(1).to_pylist()], pa.string())], names=[id_col, "text"])

    return df.selectExpr(f"`{id_col}`", f"`{ids_col}` as __ids").mapInArrow(run, f"`{id_col}` {kind}, text string")


def piece_digest(df: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per text: the number of ids with the end id, and digests of the ids and of the decoded text."""
    kind = df.schema[id_col].dataType.simpleString()
    sha = lambda b: hashlib.sha256(b).hexdigest()

    def run(batches):
        m = model(model_path)
        for batch in sliced(batches, "__text", 2 << 20):
            ids, cuts = m.encode(batch.column(1).fill_null(""))
            counts = np.diff(cuts)
            (numbers, at), (plain, begins) = m.decimal_bytes(ids), m.text_bytes(ids)
            at, begins = at[cuts].tolist(), begins[cuts].tolist()
            numbers, plain = numbers.data, plain.data
            ids = [sha(numbers[a : b - 1]) for a, b in zip(at, at[1:], strict=False)]
            texts = [sha(plain[a + (plain[a : a + 1] == b" ") : b]) for a, b in zip(begins, begins[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(ids, pa.string()), pa.array(texts, pa.string())], names=[id_col, "n_tokens", "ids_sha256", "decoded_sha256"])

    return df.selectExpr(f"`{id_col}`", f"cast(`{text_col}` as string) as __text").mapInArrow(run, f"`{id_col}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
