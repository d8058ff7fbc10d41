"""Token ids in length-delimited binary records, with a separate offset index.

A record is: length (u64), masked checksum of those 8 bytes (u32), body, masked checksum of the body
(u32), all little-endian; checksums are CRC-32, rotated and shifted so that checksums of checksums
differ. A body is: document id (i64, NULL_ID for null), bytes per id (u8: 2 where the vocabulary fits,
else 4), number of ids (u32), ids. The index file beside a data file has offset (u64), body length (u64)
and document id (i64) per record, so that readers may take records in any order.

Documents are range-partitioned and sorted by id (null ids last; rows of one id by the beginning of the text,
then as in the table), one data file per partition, so file order is id order. Null texts are empty: their only id is the end id. Repeated rows each get a record.
A text that spells an added token of the vocabulary gets that token's id, as the library has it.
"""

from __future__ import annotations

import functools
import re
import struct
import zlib
from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from packflow.llm.common import NULL_ID, id_or_last, shared_dir, sliced, storage, write_atomically
from packflow.llm.wordcache import spread

# Fixed values of the framing.
MASK_DELTA = 0xA282EAD8
HEAD, BODY, ENTRY = struct.Struct("<QI"), struct.Struct("<qBI"), np.dtype([("offset", "<u8"), ("length", "<u8"), ("doc", "<i8")])
#: Characters of a text by which rows of one id are ordered, before their place in the table.
HEAD_CHARS = 64
#: Pieces of words that a Python worker remembers.
MAX_PIECES = 500_000
#: Bytes of text that are encoded together: the more, the fewer distinct words to look up in all.
ENCODE_BYTES = 8 << 20


class RecordError(ValueError):
    pass


def masked(data) -> int:
    crc = zlib.crc32(data)
    return ((crc >> 15 | crc << 17) + MASK_DELTA) & 0xFFFFFFFF


def frame(body: bytes) -> bytes:
    length = struct.pack("<Q", len(body))
    return b"".join((length, struct.pack("<I", masked(length)), body, struct.pack("<I", masked(body))))


def unframe(data: memoryview, at: int) -> tuple[memoryview, int]:
    """(body, end of the record); raises if a checksum does not fit."""
    length, check = HEAD.unpack_from(data, at)
    if masked(data[at : at + 8]) != check:
        raise RecordError(f"the length at {at} is damaged")
    body, end = data[at + 12 : at + 12 + length], at + 16 + length
    if len(data) < end or masked(body) != struct.unpack_from("<I", data, end - 4)[0]:
        raise RecordError(f"the body at {at} is damaged")
    return body, end


def pack_body(doc: int, ids: np.ndarray, width: int) -> bytes:
    return BODY.pack(doc, width, len(ids)) + ids.astype(f"<u{width}").tobytes()


def unpack_body(body) -> tuple[int, np.ndarray]:
    doc, width, n = BODY.unpack_from(body)
    return doc, np.frombuffer(body, f"<u{width}", n, BODY.size)


class PieceMemory:
    """Pieces of text and their ids, looked up many at a time. ``learn(pieces)`` gives ids and sizes of unseen
    ones. When ``limit`` pieces are held, those met in one batch only are forgotten, and of the rest at most
    half the limit stays."""

    def __init__(self, learn: Callable[[list[str]], tuple[np.ndarray, np.ndarray]], limit: int):
        self.learn, self.limit = learn, limit
        self.texts = pa.array([], pa.string())
        self.pool, self.start, self.size, self.met = np.empty(0, np.int32), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int32)

    def shrink(self) -> None:
        keep = np.flatnonzero(self.met >= 2)
        if len(keep) > self.limit // 2:
            keep = np.sort(keep[np.argsort(-self.met[keep], kind="stable")[: self.limit // 2]])
        self.texts = self.texts.take(pa.array(keep))
        self.pool = self.pool[spread(self.start[keep], self.size[keep])]
        self.size, self.met = self.size[keep], self.met[keep] // 2
        self.start = np.cumsum(self.size) - self.size

    def places(self, pieces: pa.Array) -> np.ndarray:
        """Where each piece's ids are. Places hold until the next call."""
        place = pc.index_in(pieces, value_set=self.texts).fill_null(-1).to_numpy().astype(np.int64)
        missing = np.flatnonzero(place < 0)
        if len(missing):
            unseen = pieces.take(pa.array(missing))
            fresh = unseen.unique()
            if len(self.texts) and len(self.texts) + len(fresh) > self.limit:
                self.shrink()
                return self.places(pieces)
            ids, size = self.learn(fresh.to_numpy(zero_copy_only=False).tolist())
            place[missing] = len(self.texts) + pc.index_in(unseen, value_set=fresh).to_numpy().astype(np.int64)
            self.start = np.concatenate((self.start, len(self.pool) + np.cumsum(size) - size))
            self.size, self.pool = np.concatenate((self.size, size)), np.concatenate((self.pool, ids.astype(np.int32)))
            self.met = np.concatenate((self.met, np.zeros(len(fresh), np.int32)))
            self.texts = pa.concat_arrays([self.texts, fresh])
        here = np.zeros(len(self.texts), bool)
        here[place] = True
        self.met += here
        return place


class WordEncoder:
    """The library's ids, word by word, each distinct piece of a word encoded once.

    A blank between two characters that are no white space always begins a new pre-token, so texts may be
    cut there; unseen pieces go to the library many at a time. So is a line feed between two such
    characters a pre-token of its own; it opens the word after it. Letters with punctuation behind them
    (``SIMPLE``) are two pre-tokens and two pieces: the letters are mostly known already. Words that touch
    other white space are unsafe: their text is cut by ``CUT``. A piece is known by just what the library is
    given for it, with the blank before it, so a text's first word has pieces of its own.

    Texts that spell an added token of the vocabulary (``<|endoftext|>``, say) are left whole to the
    library, which gives that token's own id.
    """

    CUT = re.compile(r"(?<=\S) (?=\S)")
    #: ASCII and Latin-1 letters, then ASCII punctuation that is not led by an apostrophe (a contraction).
    SIMPLE = r"^(?P<head>\n?[A-Za-z\x{c0}-\x{d6}\x{d8}-\x{f6}\x{f8}-\x{ff}]+)(?P<tail>[!-&(-/:-@\[-`{-~][!-/:-@\[-`{-~]*)$"

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library, self.words = Tokenizer.from_file(path), Tokenizer.from_file(path)
        self.words.encode_special_tokens = True  # words of different texts that meet here make no token together
        self.added = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.vocab = self.library.get_vocab_size()
        self.opens = np.zeros(self.vocab, bool)
        for token, i in self.library.get_vocab().items():
            self.opens[i] = token.startswith("Ġ")
        self.memory = PieceMemory(self.learn, MAX_PIECES)

    @staticmethod
    def safe(words: pa.Array) -> pa.Array:
        """Words that are not empty and touch no white space, but for one line feed that they may begin with."""
        body = pc.replace_substring_regex(words, "^\n", "")
        return pc.and_(pc.equal(pc.utf8_trim_whitespace(body), body), pc.greater(pc.binary_length(body), 0))

    def learn(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        joined = np.fromiter((p[:1] == " " and len(p.split()) == 1 and not (p[1].isspace() or p[-1].isspace()) for p in pieces), bool, len(pieces))
        plain = [p for p, j in zip(pieces, joined.tolist(), strict=True) if j]
        flat = self.flat(["".join(plain[k : k + 256]) for k in range(0, len(plain), 256)])[0]
        starts = np.flatnonzero(self.opens[flat])
        if len(starts) != len(plain):
            raise RecordError("words and pre-tokens do not line up")
        alone, sizes = self.flat([p for p, j in zip(pieces, joined.tolist(), strict=True) if not j])
        order = np.empty(len(pieces), np.int64)  # of the pieces among plain and single ones
        order[joined], order[~joined] = np.arange(len(plain)), len(plain) + np.arange(len(sizes))
        size = np.concatenate((np.diff(np.append(starts, len(flat))), sizes))
        start = np.cumsum(size) - size
        return np.concatenate((flat, alone))[spread(start[order], size[order])], size[order]

    def flat(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        lists = [e.ids for e in self.words.encode_batch_fast(texts, add_special_tokens=False)]
        return np.fromiter(chain.from_iterable(lists), np.int32), np.fromiter(map(len, lists), np.int64, len(lists))

    def by_words(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets) of texts without added tokens."""
        lists = pc.split_pattern(pc.replace_substring(texts, "\n", " \n"), " ")  # a line feed begins a word of its own
        cuts, words = lists.offsets.to_numpy().astype(np.int64), lists.flatten().dictionary_encode()
        cuts, distinct, index = cuts - cuts[0], words.dictionary, words.indices.to_numpy()
        safe = self.safe(distinct)
        unsafe = ~safe.to_numpy(zero_copy_only=False)
        odd = np.unique(np.searchsorted(cuts[1:], np.flatnonzero(unsafe[index]), side="right")).tolist()
        cut = pc.extract_regex(distinct, self.SIMPLE)
        head, tail = (pc.struct_field(cut, k) for k in (0, 1))
        head = pc.coalesce(pc.if_else(cut.is_valid(), head, None), distinct)
        head = pc.if_else(pc.starts_with(head, "\n"), head, pc.binary_join_element_wise(" ", head, ""))
        head = pc.if_else(safe, head, "")
        tail = pc.if_else(pc.and_(cut.is_valid(), safe), tail, "").dictionary_encode()
        first = distinct.take(pa.array(index[cuts[:-1]]))
        again = [self.pieces_of(texts[k].as_py()) for k in odd]
        asked = [head, tail.dictionary, first, pa.array(list(chain.from_iterable(again)), pa.string())]
        place = self.memory.places(pa.concat_arrays(asked))
        of_head, of_tail, of_first, of_odd = np.split(place, np.cumsum([len(x) for x in asked[:-1]]))
        with_tail = pc.not_equal(tail.dictionary, "").to_numpy(zero_copy_only=False)
        tail_index = tail.indices.to_numpy()
        two = with_tail[tail_index][index]
        two[cuts[:-1]] = False
        n = 1 + two
        at = np.cumsum(n) - n
        total = int(n.sum())
        pieces = np.empty(total, np.int64)
        own = of_head[index]
        own[cuts[:-1]] = of_first
        pieces[at] = own
        pieces[at[two] + 1] = of_tail[tail_index[index[two]]]
        cuts = np.append(at, total)[cuts]
        if odd:
            parts = np.split(pieces, cuts[1:-1])
            for k, p in zip(odd, np.split(of_odd, np.cumsum([len(a) for a in again])[:-1]), strict=True):
                parts[k] = p
            pieces, cuts = np.concatenate(parts), np.append(0, np.cumsum([len(p) for p in parts]))
        size = self.memory.size[pieces]
        return self.memory.pool[spread(self.memory.start[pieces], size)], np.append(0, np.cumsum(size))[cuts]

    def pieces_of(self, text: str) -> list[str]:
        pieces = self.CUT.split(text)
        return [pieces[0], *(f" {p}" for p in pieces[1:])]

    def encode(self, texts: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, offsets), each text followed by the end id."""
        marked = np.zeros(len(texts), bool)
        for token in self.added:
            marked |= pc.match_substring(texts, token).to_numpy(zero_copy_only=False)
        ids, cuts = self.by_words(pc.if_else(pa.array(marked), "", texts) if marked.any() else texts)
        if marked.any():
            parts = np.split(ids, cuts[1:-1])
            for k in np.flatnonzero(marked).tolist():
                parts[k] = np.array(self.library.encode(texts[k].as_py(), add_special_tokens=False).ids, np.int32)
            ids, cuts = np.concatenate(parts), np.append(0, np.cumsum([len(p) for p in parts]))
        return np.insert(ids, cuts[1:], end_id), cuts + np.arange(len(cuts))


@functools.cache
def encoder(path: str) -> WordEncoder:
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # a task has one core
    return WordEncoder(path)


def write_records(docs: DataFrame, tokenizer_path: str, folder: str, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> list[Row]:
    """Write the files; (part, path, n_docs, n_tokens, bytes) of each, in order. A row per file comes back."""
    narrow = docs.select(id_or_last(id_col).alias("key"), F.col(text_col).cast("string").alias("__text"))
    ties = (F.substring("__text", 1, HEAD_CHARS).alias("head"), F.monotonically_increasing_id().alias("place"))
    order = ("key", "head", "place")  # rows of one id, or of none, may fill many ranges
    ordered = narrow.select("*", *ties).repartitionByRange(*order).sortWithinPartitions(*order).select("key", "__text")

    def write(batches):
        from pyspark import TaskContext

        m = encoder(tokenizer_path)
        width = 2 if max(m.vocab - 1, end_id) < 1 << 16 else 4
        part = TaskContext.get().partitionId()
        path, entries, tokens = f"{folder}/part-{part:08d}.records", [], 0

        def frames():
            nonlocal tokens
            offset = 0
            for batch in sliced(batches, "__text", ENCODE_BYTES):
                ids, cuts = m.encode(batch.column(1).fill_null(""), end_id)
                tokens += len(ids)
                for doc, a, b in zip(batch.column(0).to_pylist(), cuts.tolist(), cuts[1:].tolist(), strict=False):
                    body = pack_body(doc, ids[a:b], width)
                    entries.append((offset, len(body), doc))
                    offset += len(body) + 16
                    yield frame(body)

        size = write_atomically(path, frames())
        write_atomically(f"{path}.index", [np.array(entries, ENTRY).tobytes()])
        yield pa.RecordBatch.from_arrays([pa.array([part], pa.int64()), pa.array([path]), pa.array([len(entries)], pa.int64()), pa.array([tokens], pa.int64()), pa.array([size], pa.int64())], names=["part", "path", "n_docs", "n_tokens", "bytes"])

    files = ordered.mapInArrow(write, "part long, path string, n_docs long, n_tokens long, bytes long")
    return sorted((r for r in files.collect() if r.n_docs), key=lambda r: r.part)


def read_index(path: str) -> np.ndarray:
    system, name = storage(f"{path}.index")
    with system.open_input_stream(name) as f:
        return np.frombuffer(f.read(), ENTRY)


def read_record(path: str, entry: np.void) -> tuple[int, np.ndarray]:
    """One record by its index entry, for reads in any order."""
    system, name = storage(path)
    with system.open_input_file(name) as f:
        data = memoryview(f.read_at(int(entry["length"]) + 16, int(entry["offset"])))
    return unpack_body(unframe(data, 0)[0])


def read_file(path: str, chunk: int = 16 << 20) -> Iterator[tuple[int, np.ndarray]]:
    """All records of a file in order, a bounded stretch of it in memory at a time."""
    index = read_index(path)
    system, name = storage(path)
    with system.open_input_file(name) as f:
        first = 0
        while first < len(index):
            begin = int(index["offset"][first])
            last = max(first + 1, int(np.searchsorted(index["offset"], begin + chunk)))
            stop = int(index["offset"][last - 1] + index["length"][last - 1]) + 16
            data, at = memoryview(f.read_at(stop - begin, begin)), 0
            for k in range(first, last):
                body, end = unframe(data, at)
                if len(body) != index["length"][k] or begin + at != index["offset"][k]:
                    raise RecordError("index and records do not agree")
                yield unpack_body(body)
                at = end
            first = last


def read_digest(spark: SparkSession, files: list[Row], id_col: str = "doc_id") -> DataFrame:
    """(id, start, n_tokens, ids_crc32) read back from the files; start counts all ids before."""
    base, plan = 0, []
    for r in files:
        plan.append((r.path, base))
        base += r.n_tokens
    schema = f"`{id_col}` long, start long, n_tokens long, ids_crc32 long"
    if not plan:
        return spark.createDataFrame([], schema)

    def read(batches):
        for batch in batches:
            for path, start in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                rows, at = [], start
                for doc, ids in read_file(path):
                    rows.append((None if doc == NULL_ID else doc, at, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    at += len(ids)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=[id_col, "start", "n_tokens", "ids_crc32"])

    return spark.createDataFrame(plan, "path string, start long").repartition(min(len(plan), 20_000)).mapInArrow(read, schema)


def record_digest(docs: DataFrame, tokenizer_path: str, end_id: int = 2) -> DataFrame:
    spark = docs.sparkSession
    return read_digest(spark, write_records(docs, tokenizer_path, shared_dir(spark, "records"), end_id))
