"""WARC archives: write one record per page, and read archives back by boundary-chain verification.

Writing: payloads of at least ``LEAST_REVISIT`` bytes that are equal share one response record, that of
the least page id; the others become revisit records that refer to it. Each task writes one file to the
shared folder under a temporary name and renames it.

Reading: tasks scan blocks of the files for the record magic and emit, for each place where a whole
record parses, the offset of its successor. Inside a block these chains are contracted to where they
leave it; across blocks, pointer jumping from the start of each file (doubling joins, checkpointed)
keeps only what the chain reaches, so that magic inside payloads is rejected. A last pass reads the
records from each block's verified entry to where its chain leaves the block. Files of one block take the
same way. Records may span blocks. A chain that breaks before the end of its file is an error.

Hot payloads: the digests of most copies, at most ``HOT_DIGESTS`` of them by their share of all pages, are
broadcast; the pages of the others meet their group in a join, whose largest group that share bounds.

Null html is an empty payload. Equal smallest page ids are all responses; a null page id is a response
only if no id in its group is known. Repeated rows each get a record.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from packflow.llm.common import materialize, shared_dir, sliced, storage, text_bytes, write_atomically

LEAST_REVISIT = 100
#: Digests whose copies are more than this fraction of all pages are fewer than it, 40 bytes each.
HOT_DIGESTS = 100_000
BLOCK = 8 << 20
# Fixed values of the WARC and gzip formats.
MAGIC, END = b"WARC/1.1\r\n", b"\r\n\r\n"
GZIP_MAGIC = b"\x1f\x8b\x08"
REVISIT_PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
DATE = "2024-01-01T00:00:00Z"


class WarcError(ValueError):
    pass


def page_urn(page_id: int | None) -> str:
    return f"<urn:page:{'' if page_id is None else page_id}>"


def build_record(page_id: int | None, url: str, payload: bytes, digest: str, refers_to: int | None, revisit: bool) -> bytes:
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    fields = [
        ("WARC-Type", "revisit" if revisit else "response"), ("WARC-Record-ID", page_urn(page_id)), ("WARC-Date", DATE),
        ("WARC-Target-URI", re.sub(r"[\x00-\x20\x7f]", lambda m: f"%{ord(m[0]):02X}", url)),
        ("WARC-Payload-Digest", f"sha256:{digest}"), ("X-Payload-Length", str(len(payload))),
        ("Content-Type", "application/http;msgtype=response"), ("Content-Length", str(len(block))),
    ]
    if revisit:
        fields += [("WARC-Refers-To", page_urn(refers_to)), ("WARC-Profile", REVISIT_PROFILE)]
    return MAGIC + "".join(f"{k}: {v}\r\n" for k, v in fields).encode() + b"\r\n" + block + END


class Reader:
    """A file's bytes from an offset on, read as far as asked."""

    def __init__(self, uri: str, start: int, ahead: int):
        system, path = storage(uri)
        self.file, self.start, self.data, self.ahead = system.open_input_file(path), start, b"", ahead
        self.size = self.file.size()

    def upto(self, end: int) -> bytes:
        """The bytes held, reaching ``end`` if the file does."""
        end = min(end, self.size)
        have = self.start + len(self.data)
        if end > have:
            end = min(self.size, max(end, have + self.ahead))
            self.data += self.file.read_at(end - have, have)
        return self.data

    def plain_record(self, offset: int) -> tuple[int, bytes, int] | None:
        """(successor, record bytes, header length) if a whole record begins here."""
        at, want = offset - self.start, 4096
        while True:
            data = self.upto(offset + want)
            if not data.startswith(MAGIC, at):
                return None
            head = data.find(END, at)
            if head >= 0:
                break
            if offset + want >= self.size or want > 1 << 20:
                return None
            want *= 4
        found = re.search(rb"\r\nContent-Length: *([0-9]{1,18})(?=\r\n)", data[at : head + 2], re.IGNORECASE)
        if not found:
            return None
        stop = head + 4 + int(found[1])
        if self.start + stop + 4 > self.size:
            return None
        data = self.upto(self.start + stop + 4)
        return (self.start + stop + 4, data[at:stop], head + 4 - at) if data[stop : stop + 4] == END else None

    def gzip_record(self, offset: int) -> tuple[int, bytes, int] | None:
        engine, out, at = zlib.decompressobj(31), [], offset
        try:
            while not engine.eof:
                if at >= self.size:
                    return None
                data = self.upto(at + (1 << 16))
                piece = data[at - self.start : at - self.start + (1 << 16)]
                out.append(engine.decompress(piece))
                at += len(piece)
                if len(out) == 1 and not out[0].startswith(MAGIC[: len(out[0])]):
                    return None
        except zlib.error:
            return None
        record = b"".join(out)
        head = record.find(END)
        if not record.startswith(MAGIC) or head < 0 or not record.endswith(END):
            return None
        return at - len(engine.unused_data), record[:-4], head + 4

    def record(self, offset: int, gzip: bool) -> tuple[int, bytes, int] | None:
        return self.gzip_record(offset) if gzip else self.plain_record(offset)


def candidates(reader: Reader, start: int, end: int, gzip: bool) -> Iterator[tuple[int, int]]:
    """(offset, successor) wherever in the block a whole record parses."""
    magic = GZIP_MAGIC if gzip else MAGIC
    at = -1
    while True:
        data = reader.upto(min(end, reader.size) + len(magic))
        at = data.find(magic, at + 1)
        if at < 0 or reader.start + at >= end:
            return
        if found := reader.record(reader.start + at, gzip):
            yield reader.start + at, found[0]


def contracted(pairs: list[tuple[int, int]], end: int, size: int) -> list[tuple[int, int]]:
    """Each candidate with where its chain leaves the block; chains that break inside are dropped."""
    leaves: dict[int, int] = {}
    for offset, successor in reversed(pairs):
        out = successor if successor >= min(end, size) else leaves.get(successor)
        if out is not None:
            leaves[offset] = out
    return sorted(leaves.items())


def write_archives(pages: DataFrame, folder: str, gzip: bool = True, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(path, bytes) of the files written, materialized. One shuffle, of compressed payloads."""
    html = F.coalesce(F.col(html_col).cast("string"), F.lit("")).cast("binary")
    shared = (
        pages.select(F.col(id_col).cast("long").alias("page"), F.octet_length(html).alias("n"), F.unhex(F.sha2(html, 256)).alias("digest"))
        .where(F.col("n") >= LEAST_REVISIT)
        .groupBy("digest")
        .agg(F.min("page").alias("first"), F.count(F.lit(1)).alias("copies"))
        .where("copies > 1")
    )
    shared = materialize(shared, "warc-shared")
    copies = shared.agg(F.sum("copies")).first()[0] or 0
    hot = F.col("copies") > max(1000, copies // HOT_DIGESTS)

    def pack(batches):
        for batch in sliced(batches, "html", 16 << 20):
            payloads = text_bytes(batch.column(2))
            digests = [hashlib.sha256(p).digest() for p in payloads]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(digests, pa.binary()), pa.array([zlib.compress(p, 1) for p in payloads], pa.binary())], names=["page", "url", "digest", "packed"])

    narrow = pages.select(F.col(id_col).cast("long").alias("page"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.col(html_col).cast("string").alias("html"))
    packed = narrow.mapInArrow(pack, "page long, url string, digest binary, packed binary")
    packed = packed.join(F.broadcast(shared.where(hot).select("digest", F.col("first").alias("hot_first"), F.lit(True).alias("hot"))), "digest", "left")
    # a page of a hot payload is done; its key is its own from here on, so that copies do not crowd into a task
    key = F.when(F.col("hot"), F.unhex(F.sha2(F.concat("digest", F.monotonically_increasing_id().cast("string").cast("binary")), 256))).otherwise(F.col("digest"))
    rest = shared.where(~hot).select(F.col("digest").alias("key"), "first")
    packed = packed.withColumn("key", key).join(rest, "key", "left").select("page", "url", "digest", "packed", F.coalesce("hot_first", "first").alias("first"))

    def write(batches):
        from pyspark import TaskContext

        def records():
            for batch in batches:
                for page, url, digest, body, first in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                    payload = zlib.decompress(body)
                    revisit = len(payload) >= LEAST_REVISIT and first is not None and page != first
                    record = build_record(page, url, payload, digest.hex(), first, revisit)
                    if gzip:
                        engine = zlib.compressobj(1, zlib.DEFLATED, 31)
                        record = engine.compress(record) + engine.flush()
                    yield record

        path = f"{folder}/part-{TaskContext.get().partitionId():06d}.warc{'.gz' if gzip else ''}"
        size = write_atomically(path, records())
        yield pa.RecordBatch.from_arrays([pa.array([path]), pa.array([size], pa.int64())], names=["path", "bytes"])

    return materialize(packed.mapInArrow(write, "path string, bytes long").where("bytes > 0"), "warc-files")


def read_archives(files: DataFrame, gzip: bool = True, block: int = BLOCK) -> DataFrame:
    """(path, offset, headers, payload) of every record that the chain from its file's start reaches."""
    many = files.agg(F.coalesce(F.max(F.ceil(F.col("bytes") / block)), F.lit(0)), F.coalesce(F.sum(F.ceil(F.col("bytes") / block)), F.lit(0))).first()
    most, total = int(many[0]), int(many[1])
    blocks = files.where("bytes > 0").select("path", F.explode(F.sequence(F.lit(0).cast("long"), F.col("bytes") - 1, F.lit(block).cast("long"))).alias("start"))
    blocks = blocks.repartition(max(1, min(total, 20_000)))

    def scan(batches):
        for batch in batches:
            for path, start in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                reader = Reader(path, start, block)
                edges = contracted(list(candidates(reader, start, start + block, gzip)), start + block, reader.size)
                yield pa.RecordBatch.from_arrays([pa.array([path] * len(edges), pa.string()), pa.array([e[0] for e in edges], pa.int64()), pa.array([e[1] for e in edges], pa.int64())], names=["path", "src", "dst"])

    reached = files.where("bytes > 0").select("path", F.lit(0).cast("long").alias("at"))
    edges = materialize(blocks.mapInArrow(scan, "path string, src long, dst long"), "warc-edges")
    entries = edges.select("path", F.col("dst").alias("src")).union(reached.select("path", F.col("at").alias("src"))).distinct()
    jump = direct = materialize(edges.join(entries, ["path", "src"], "left_semi"), "warc-jump")
    for k in range(max(1, (most - 1).bit_length())):
        step = reached.join(jump, (reached.path == jump.path) & (reached["at"] == jump.src)).select(reached.path, F.col("dst").alias("at"))
        reached = materialize(reached.union(step).distinct(), "warc-reached")
        if 2 << k < most:
            a, b = jump.alias("a"), jump.alias("b")
            jump = materialize(a.join(b, (F.col("a.path") == F.col("b.path")) & (F.col("a.dst") == F.col("b.src"))).select("a.path", "a.src", "b.dst"), "warc-jump")
    leaves = direct.select("path", F.col("src").alias("at"), F.col("dst").alias("until"))
    ends = files.select("path", F.col("bytes").alias("at"))
    reached = reached.join(ends, ["path", "at"], "left_anti").join(leaves, ["path", "at"], "left")

    def walk(batches):
        for batch in batches:
            for path, start, until in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                at, rows, held = start, [], 0
                if until is None:
                    raise WarcError(f"the chain of {path} breaks in the block of {start}")
                reader = Reader(path, start, block)
                while at < until:
                    found = reader.record(at, gzip)
                    if not found:
                        raise WarcError(f"the chain of {path} breaks at {at}")
                    after, record, head = found
                    headers = dict(line.split(": ", 1) for line in record[:head].decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
                    cut = record.find(END, head)
                    payload = record[cut + 4 :] if cut >= 0 and headers.get("Content-Type", "").startswith("application/http") else record[head:]
                    rows.append((path, at, list(headers.items()), payload))
                    at, held = after, held + len(payload)
                    if held > 16 << 20:
                        yield as_batch(rows)
                        rows, held = [], 0
                yield as_batch(rows)

    def as_batch(rows):
        types = [pa.string(), pa.int64(), pa.map_(pa.string(), pa.string()), pa.binary()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 4, types, strict=True)], names=["path", "offset", "headers", "payload"])

    spread = reached.repartition(max(1, min(total, 20_000)))
    return spread.mapInArrow(walk, "path string, offset long, headers map<string,string>, payload binary")


def page_records(pages: DataFrame, gzip: bool = True, block: int = BLOCK) -> DataFrame:
    """Write the pages to archives, read these, and tell what each page's record says."""
    files = write_archives(pages, shared_dir(pages.sparkSession, "warc"), gzip)
    number = lambda name: F.regexp_extract(F.col("headers")[name], r"([0-9-]+)>$", 1)
    as_id = lambda c: F.when(c == "", None).otherwise(c).cast("long")
    kind = F.col("headers")["WARC-Type"]
    told = F.regexp_replace(F.col("headers")["WARC-Payload-Digest"], "^sha256:", "")
    return read_archives(files, gzip, block).select(
        as_id(number("WARC-Record-ID")).alias("page_id"),
        F.when(kind == "revisit", F.col("headers")["X-Payload-Length"].cast("long")).otherwise(F.octet_length("payload").cast("long")).alias("payload_bytes"),
        F.when(kind == "revisit", told).otherwise(F.sha2("payload", 256)).alias("payload_digest"),
        kind.alias("record_type"),
        as_id(number("WARC-Refers-To")).alias("refers_to"),
    )
