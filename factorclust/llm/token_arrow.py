"""Token ids in Arrow files whose batches hold fixed-size lists: equal-length sequences and their masks.

Each shard of the documents, in ascending order of doc_id, gives one Arrow file. Its ids, end to end, fill
rows of ``length`` ids; the last row is padded, and the mask column says which ids count. Rows have one
size, so id p of a shard is in row p // length at p % length, and a memory-mapped file gives any row
without a copy. A second Arrow file beside it says where each document begins. Files get their final name
when they are complete; an attempt that is lost leaves only a file that no manifest row names.

Null or empty texts have their end id alone; equal doc_ids keep an order by the texts' checksums; repeated
rows are written each by itself; an empty table gives no rows.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from factorclust.llm.shared import cut, fresh_path, tidy
from factorclust.llm.tokens import encoder

LENGTH = 2048
#: Rows of a batch, and documents of a batch of the index.
BATCH, INDEX_BATCH = 128, 16_384
_INDEX = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64())])


def schema(length: int, dtype: np.dtype) -> pa.Schema:
    return pa.schema([pa.field("ids", pa.list_(pa.from_numpy_dtype(dtype), length), False), pa.field("mask", pa.list_(pa.bool_(), length), False)])


class Writer:
    """One file of sequences; ids come in pieces of any size and leave in batches of BATCH rows."""

    def __init__(self, sink, length: int, dtype: np.dtype):
        self.length, self.dtype, self.schema = length, dtype, schema(length, dtype)
        self.out = pa.ipc.new_file(sink, self.schema)
        self.held, self.room = [], BATCH * length

    def add(self, ids: np.ndarray) -> None:
        while len(ids) >= self.room:
            self.held.append(ids[: self.room])
            ids = ids[self.room :]
            self._flush()
        self.held.append(ids)
        self.room -= len(ids)

    def _flush(self) -> None:
        flat = np.concatenate(self.held) if self.held else np.zeros(0, self.dtype)
        rows = -(-len(flat) // self.length)
        mask = np.arange(rows * self.length) < len(flat)
        full = np.zeros(rows * self.length, self.dtype)
        full[: len(flat)] = flat
        if rows:
            lists = [pa.FixedSizeListArray.from_arrays(pa.array(x), type=f.type) for x, f in zip((full, mask), self.schema, strict=True)]
            self.out.write_batch(pa.RecordBatch.from_arrays(lists, schema=self.schema))
        self.held, self.room = [], BATCH * self.length

    def close(self) -> None:
        self._flush()
        self.out.close()


class Reader:
    """Random access to the sequences of one file; memory-mapped where the file is local."""

    def __init__(self, source):
        self.file = pa.ipc.open_file(source)
        self.length = self.file.schema.field("ids").type.list_size
        self.at = (-1, None)

    def batch(self, k: int) -> pa.RecordBatch:
        if self.at[0] != k:
            self.at = (k, self.file.get_batch(k))
        return self.at[1]

    def row(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids (a view of the file) and mask of sequence i."""
        b, k = self.batch(i // BATCH), i % BATCH
        ids = b.column(0).flatten().to_numpy(zero_copy_only=True)[k * self.length : (k + 1) * self.length]
        return ids, b.column(1).flatten().to_numpy(zero_copy_only=False)[k * self.length : (k + 1) * self.length]

    def span(self, start: int, n: int) -> Iterator[np.ndarray]:
        """The ids start..start+n-1 of the shard, batch by batch."""
        size = BATCH * self.length
        while n > 0:
            lo = start % size
            part = self.batch(start // size).column(0).flatten().to_numpy(zero_copy_only=True)[lo : lo + n]
            yield part
            start, n = start + len(part), n - len(part)


def _place(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri)


def open_reader(uri: str) -> Reader:
    system, path = _place(uri)
    return Reader(pa.memory_map(path) if isinstance(system, pafs.LocalFileSystem) else system.open_input_file(path))


def write(documents: DataFrame, tokenizer: str, to: str, length: int = LENGTH, shards: int | None = None) -> DataFrame:
    """Writes the files below ``to``; the manifest has a row for each: shard, uri, docs, tokens, start (of the shard)."""
    spark = documents.sparkSession
    n = shards or max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    order = ["doc_id", F.crc32(F.col("text").cast("binary"))]
    dealt = rows.repartitionByRange(n, *order).sortWithinPartitions(*order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        code, shard = encoder(tokenizer), TaskContext.get().partitionId()
        system, top = _place(to)
        first = next((b for b in batches if b.num_rows), None)
        if first is None:
            return
        system.create_dir(top, recursive=True)
        stem = f"{top}/{shard:06d}-{uuid.uuid4().hex[:12]}"
        docs = tokens = 0
        with system.open_output_stream(f"{stem}.tmp") as sink, system.open_output_stream(f"{stem}.index.tmp") as index_sink:
            out, index = Writer(sink, length, code.dtype), pa.ipc.new_file(index_sink, _INDEX)
            held: list[tuple[int | None, int, int]] = []

            def flush() -> None:
                index.write_batch(pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held, strict=True), _INDEX, strict=True)], schema=_INDEX))
                held.clear()

            def all_batches() -> Iterator[pa.RecordBatch]:
                yield first
                yield from batches

            for batch in all_batches():
                for doc, ids in zip(batch.column(0).to_pylist(), code.encode_many(batch.column(1).to_pylist()), strict=True):
                    out.add(ids)
                    held.append((doc, tokens, len(ids)))
                    docs, tokens = docs + 1, tokens + len(ids)
                    if len(held) == INDEX_BATCH:
                        flush()
            if held:
                flush()
            out.close()
            index.close()
        for kind in ("index.", ""):
            system.move(f"{stem}.{kind}tmp", f"{stem}.{kind}arrow")
        scheme = to[: len(to) - len(top)] if to.endswith(top) else ""
        yield pa.RecordBatch.from_pydict({"shard": [shard], "uri": [f"{scheme}{stem}.arrow"], "docs": [docs], "tokens": [tokens]})

    manifest = cut(dealt.mapInArrow(tidy(run), "shard long, uri string, docs long, tokens long"), "manifest")
    # one row a file
    return manifest.withColumn("start", F.sum("tokens").over(Window.orderBy("shard")) - F.col("tokens"))


def read(manifest: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files that the manifest names."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for uri, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                data = open_reader(uri)
                system, path = _place(uri)
                with system.open_input_file(path.removesuffix("arrow") + "index.arrow") as source:
                    index = pa.ipc.open_file(source)
                    for k in range(index.num_record_batches):
                        b = index.get_batch(k)
                        crcs = []
                        for at, n in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                            crc = 0
                            for part in data.span(at, n):
                                crc = zlib.crc32(part.astype("<u4").tobytes(), crc)
                            crcs.append(crc)
                        starts = pa.array(b.column(1).to_numpy() + start, pa.int64())
                        yield pa.RecordBatch.from_arrays([b.column(0), starts, b.column(2), pa.array(crcs, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    n = max(int(manifest.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    return manifest.select("uri", "start").repartition(n).mapInArrow(tidy(run), "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(documents: DataFrame, tokenizer: str, length: int = LENGTH) -> DataFrame:
    return read(write(documents, tokenizer, fresh_path(documents.sparkSession, "tokens"), length))
