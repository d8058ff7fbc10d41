"""Python data sources: synthetic keyed texts to read, packed vector files to write."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage

from packflow.sources.corpora import lognormal_sizes


class LognormalTexts(DataSource):
    """``spark.read.format("lognormal_texts").options(parts=, texts=, sigma=, tasks=)``: (part_key, seq, text)
    in key order, with log-normal partition sizes."""

    @classmethod
    def name(cls) -> str:
        return "lognormal_texts"

    def schema(self) -> str:
        return "part_key string, seq long, text string"

    def reader(self, schema) -> DataSourceReader:
        return LognormalReader(self.options)


class KeyRange(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class LognormalReader(DataSourceReader):
    def __init__(self, options):
        self.parts, self.texts = int(options.get("parts", 400)), int(options.get("texts", 60_000))
        self.sigma, self.tasks = float(options.get("sigma", 1.72)), int(options.get("tasks", 8))

    def partitions(self):
        """Key ranges of about even texts."""
        ends = np.cumsum(lognormal_sizes(self.parts, self.texts, self.sigma))
        cuts = np.unique(np.searchsorted(ends, np.linspace(0, self.texts, self.tasks + 1)[1:-1]))
        cuts = [0, *(cuts + 1).tolist(), self.parts]
        return [KeyRange(a, b) for a, b in zip(cuts, cuts[1:], strict=False) if b > a]

    def read(self, partition: KeyRange):
        sizes = lognormal_sizes(self.parts, self.texts, self.sigma)
        for k in range(partition.low, partition.high):
            for low in range(0, sizes[k], 10_000):
                seq = np.arange(low, min(sizes[k], low + 10_000))
                yield pa.RecordBatch.from_arrays([pa.array([f"k{k + 1:05d}"] * len(seq)), pa.array(seq + 1), pa.array([f"item {k % 97} brand {s % 25} type {s % 150} size {s % 50}" for s in seq.tolist()])], names=["part_key", "seq", "text"])


class PackedVectors(DataSource):
    """``df.write.format("packed_vectors").option("path", ...)``: one file of vectors and one boundary index
    per task in place of a file per key, for very many keys. Rows must come in key order."""

    @classmethod
    def name(cls) -> str:
        return "packed_vectors"

    def schema(self) -> str:
        return "part_key string, seq long, embedding array<float>"

    def writer(self, schema, overwrite: bool) -> DataSourceArrowWriter:
        return PackedWriter(self.options["path"])


class Written(WriterCommitMessage):
    def __init__(self, files: list[str]):
        self.files = files


class PackedWriter(DataSourceArrowWriter):
    """Files get their final names only when the whole job commits."""

    def __init__(self, path: str):
        self.path = path if "://" in path else f"file://{path}"

    def write(self, iterator) -> Written:
        from pyspark import TaskContext

        from packflow.operators.encode import key_runs
        from packflow.operators.sink import filesystem, write_table

        stem, system, runs, n = None, None, [], 0
        for batch in iterator:
            if not batch.num_rows:
                continue
            if stem is None:
                stem = f"{self.path}/_staged/{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}"
                system, path = filesystem(f"{stem}.vectors.parquet")
                system.create_dir(path.rsplit("/", 1)[0], recursive=True)
                out = system.open_output_stream(path)
                writer = pq.ParquetWriter(out, batch.select(["seq", "embedding"]).schema)
            for k, a, b in key_runs(batch.column(batch.schema.get_field_index("part_key"))):
                if runs and runs[-1]["part_key"] == k and runs[-1]["end"] == n + a:
                    runs[-1]["end"] = n + b
                else:
                    runs.append({"part_key": k, "start": n + a, "end": n + b})
            writer.write_batch(batch.select(["seq", "embedding"]))  # a row group each: no more than that is held
            n += batch.num_rows
        if stem is None:
            return Written([])
        writer.close()
        out.close()
        index = pa.schema([("part_key", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
        write_table(f"{stem}.index.parquet", pa.Table.from_pylist(runs, schema=index))
        return Written([f"{stem}.vectors.parquet", f"{stem}.index.parquet"])

    def commit(self, messages) -> None:
        from packflow.operators.sink import filesystem

        for m in messages:
            for uri in m.files if m else ():
                system, path = filesystem(uri)
                system.move(path, path.replace("/_staged/", "/"))

    def abort(self, messages) -> None:
        from packflow.operators.sink import filesystem

        for m in messages:
            for uri in m.files if m else ():
                system, path = filesystem(uri)
                system.delete_file(path)


def read_packed(spark, root: str):
    """(part_key, seq, embedding): a file's rows get their key from its boundary index, by place. The index
    has a row for each key and file, and its file's name joins the two."""
    from pyspark.sql import functions as F

    stem = lambda c: F.regexp_extract(c, r"([^/]+)\.(vectors|index)\.parquet$", 1)
    index = spark.read.schema("part_key string, start long, end long").option("pathGlobFilter", "*.index.parquet").parquet(root)
    index = index.select(stem(F.col("_metadata.file_path")).alias("stem"), "part_key", "start", "end")
    rows = spark.read.schema("seq long, embedding array<float>").option("pathGlobFilter", "*.vectors.parquet").parquet(root)
    rows = rows.select(stem(F.col("_metadata.file_path")).alias("stem"), F.col("_metadata.row_index").alias("at"), "seq", "embedding")
    return rows.join(index, (rows.stem == index.stem) & (rows["at"] >= index.start) & (rows["at"] < index.end)).select("part_key", "seq", "embedding")


def register(spark) -> None:
    spark.dataSource.register(LognormalTexts)
    spark.dataSource.register(PackedVectors)
