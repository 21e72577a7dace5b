"""Nearest neighbours by randomly rotated one-bit codes.

Vectors are centred, divided by their length and turned by a random rotation; the signs, packed into words, are
the code, and two scalars correct it: the distance to the centre and the code's inner product with its own
vector. A query, turned alike, is rounded to a few bit planes, so its inner product with a code is a few
counts of common bits; with the scalars that estimates the inner product with the vector, with an error of
known spread. Rows whose lower bound lies above the k-th smallest upper bound seen so far are passed over; the
rest are compared exactly, on the original vectors in double precision, summed in order of their components.

Every row is indexed; the index is written to the shared folder once. Rows and queries meet in blocks: a block
of rows with a block of queries is one group, the k best of each query and block leave it, and the best of
those are the result.

Vectors that are null, zero, or hold null or non-finite components take no part. Vectors of each width are a
space of their own: neighbours have the query's width. Equal distances go to the smaller vec_id; repeated rows
are candidates each by itself, and each row of a repeated query has its own k neighbours, the other copies
among them. Rows without an id take no part. No rows, no result; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, FloatType

from factorclust.llm.shared import cut, tidy

#: Spread of the bounds, in units of the estimate's standard error; a miss needs an error beyond it.
EPSILON = 3.0
#: Bit planes of a rounded query.
PLANES = 6
#: Queries and rows of a group; queries and rows whose estimates are made at once.
QUERY_BLOCK, ROW_BLOCK = 4_096, 8_192
Q_TILE, TILE = 512, 1_024
#: Widths of vectors that may be mixed; each has a centre and a rotation.
WIDTHS = 256


def usable(c: Column) -> Column:
    x = c.cast("array<double>")
    fine = F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return c.isNotNull() & (F.size(x) > 0) & F.coalesce(fine, F.lit(False)) & F.coalesce(F.exists(x, lambda v: v != 0), F.lit(False))


def rotation(d: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((d, d)))
    return q * np.sign(np.diag(r))


def centre(vectors: DataFrame, d: int) -> np.ndarray:
    """The mean vector; each partition sends one row of d sums."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(d), 0
        for b in batches:
            x = b.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            total += x.sum(0)
            n += len(x)
        yield pa.RecordBatch.from_pydict({"i": np.arange(d), "s": total, "n": np.full(d, n)})

    rows = vectors.select("v").mapInArrow(sums, "i long, s double, n long").groupBy("i").agg((F.sum("s") / F.sum("n")).alias("m")).collect()  # d rows
    mean = np.zeros(d)
    for r in rows:
        mean[r.i] = r.m
    return mean


def pack(bits: np.ndarray) -> np.ndarray:
    """Rows of bits as 64-bit words; the last word is filled up with 0."""
    packed = np.packbits(bits, axis=1)
    return np.pad(packed, ((0, 0), (0, -packed.shape[1] % 8))).view(np.uint64)


def encode(x: np.ndarray, mean: np.ndarray, turn: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(codes as words, distances to the centre, inner products of the codes with their vectors)."""
    y = x - mean
    length = np.sqrt((y * y).sum(1))
    turned = (y / np.where(length > 0, length, 1)[:, None]) @ turn
    return pack(turned > 0), length, np.abs(turned).sum(1) / np.sqrt(x.shape[1])


class Queries:
    """Turned queries as bit planes: component = low + step * (sum of 2^j * bit j) + error."""

    def __init__(self, q: np.ndarray, mean: np.ndarray, turn: np.ndarray, planes: int = PLANES):
        y = q - mean
        self.d = q.shape[1]
        self.length = np.sqrt((y * y).sum(1))
        turned = (y / np.where(self.length > 0, self.length, 1)[:, None]) @ turn
        self.low = turned.min(1)
        self.step = np.maximum(turned.max(1) - self.low, 1e-12) / ((1 << planes) - 1)
        rounded = np.rint((turned - self.low[:, None]) / self.step[:, None]).astype(np.int64)
        self.planes = [pack((rounded >> j) & 1 == 1) for j in range(planes)]
        self.total = rounded.sum(1)
        self.error = np.sqrt(((turned - self.low[:, None] - self.step[:, None] * rounded) ** 2).sum(1))

    def inner(self, some: slice, codes: np.ndarray) -> np.ndarray:
        """Estimated inner products of the unit queries with the codes' signs over sqrt(d), queries by codes."""
        n = len(self.length[some])
        whole = np.int16 if self.d << len(self.planes) < 1 << 15 else np.int32
        common = np.zeros((n, len(codes)), whole)
        for j, plane in enumerate(self.planes):
            for w in range(codes.shape[1]):
                common += np.multiply(np.bitwise_count(plane[some, w][:, None] & codes[None, :, w]), 1 << j, dtype=whole)
        ones = np.bitwise_count(codes).sum(1).astype(np.float64)
        low, step = self.low[some][:, None], self.step[some][:, None]
        # the sum over bits that are set, twice, less the sum over all
        return (low * (2 * ones[None, :] - self.d) + step * (2.0 * common - self.total[some][:, None])) / np.sqrt(self.d)


def bounds(codes: np.ndarray, length: np.ndarray, inner: np.ndarray, q: Queries, some: slice, eps: float) -> tuple[np.ndarray, np.ndarray]:
    """Lower and upper bounds of the squared distances, queries by rows."""
    safe = np.maximum(inner, 1e-9)
    about = q.inner(some, codes) / safe[None, :]
    spread = eps * np.sqrt(np.maximum(0, 1 - safe**2)) / safe / np.sqrt(max(1, q.d - 1))
    q_length = q.length[some]
    base = length[None, :] ** 2 + q_length[:, None] ** 2
    cross = 2 * length[None, :] * q_length[:, None]
    slack = cross * (spread[None, :] + q.error[some][:, None] / safe[None, :] + 1e-9) + 1e-9 * base
    return base - cross * about - slack, base - cross * about + slack


def distances(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Euclidean distances of rows to one vector; squares are added in order of the components."""
    diff = x.astype(np.float64).T - q[:, None]
    return np.sqrt(np.add.accumulate(diff * diff, axis=0)[-1])


def _best(score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    return np.lexsort((ids, score))[:k]


def search_block(q_row: np.ndarray, q: np.ndarray, row: np.ndarray, row_id: np.ndarray, x: np.ndarray, codes, length, inner, mean: np.ndarray, turn: np.ndarray, k: int, eps: float) -> list[tuple[int, int, float]]:
    """(query number, number of a row here, distance) of the k nearest rows of this block for each query; never the query's own row."""
    asked = Queries(q, mean, turn)
    found: list[tuple[np.ndarray, np.ndarray]] = [(np.zeros(0), np.zeros(0, np.int64))] * len(q)
    kth = np.full(len(q), np.inf)  # of the upper bounds, then of the exact squared distances
    for lo in range(0, len(x), TILE):
        t = slice(lo, lo + TILE)
        for first in range(0, len(q), Q_TILE):
            some = slice(first, first + Q_TILE)
            low, high = bounds(codes[t], length[t], inner[t], asked, some, eps)
            if high.shape[1] > k:
                kth[some] = np.minimum(kth[some], np.partition(high, k, axis=1)[:, k])  # one more than k: the query may be among them
            near = low <= kth[some][:, None]
            for i in np.flatnonzero(near.any(1)):
                at = np.flatnonzero(near[i]) + lo
                i += first
                at = at[row[at] != q_row[i]]
                if not len(at):
                    continue
                score, at = np.concatenate([found[i][0], distances(x[at], q[i])]), np.concatenate([found[i][1], at])
                keep = _best(score, row_id[at], k)
                found[i] = (score[keep], at[keep])
                if len(keep) == k:
                    kth[i] = min(kth[i], score[keep[-1]] ** 2 * (1 + 1e-9))
    return [(i, int(a), float(s)) for i, (score, at) in enumerate(found) for s, a in zip(score, at, strict=True)]


def _matrix(column: pa.ChunkedArray | pa.Array, d: int) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return flat.flatten().to_numpy(zero_copy_only=False).reshape(-1, d)


def _words(column: pa.ChunkedArray, n: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint64).reshape(n, -1)


def nearest(vectors: DataFrame, is_query: Column, k: int = 10, eps: float = EPSILON, seed: int = 7, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest other rows of every row where ``is_query`` holds."""
    kind = vectors.schema[vec_col].dataType
    stored = "float" if isinstance(kind, ArrayType) and isinstance(kind.elementType, FloatType) else "double"
    rows = vectors.where(usable(F.col(vec_col))).select(
        F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast(f"array<{stored}>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"),
    ).where(F.col("id").isNotNull())
    shapes = rows.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n"), F.count_if("q").alias("nq")).orderBy("d").limit(WIDTHS + 1).collect()
    if len(shapes) > WIDTHS:
        raise ValueError(f"vectors of more than {WIDTHS} widths")
    found = [_nearest(rows.where(F.size("v") == s.d), s.d, s.n, s.nq, stored, k, eps, seed) for s in shapes if s.nq]
    if not found:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    return reduce(DataFrame.unionByName, found)


def _nearest(rows: DataFrame, d: int, n: int, nq: int, stored: str, k: int, eps: float, seed: int) -> DataFrame:
    mean, turn = centre(rows, d), rotation(d, seed)
    row_blocks, query_blocks = -(-n // ROW_BLOCK), -(-nq // QUERY_BLOCK)
    held = rows.sparkSession.sparkContext.broadcast((mean, turn))

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mean, turn = held.value
        for b in batches:
            codes, length, inner = encode(_matrix(b.column(2), d), mean, turn)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(length), pa.array(inner)], names=["row", "id", "v", "q", "code", "length", "inner"])

    numbered = rows.select(F.monotonically_increasing_id().alias("row"), "id", "v", "q")
    # written, so the numbers that tell rows apart stay as they are
    coded = cut(numbered.mapInArrow(tidy(index), f"row long, id long, v array<{stored}>, q boolean, code binary, length double, inner double"), "codes")
    block = lambda blocks, salt: F.pmod(F.xxhash64("row", F.lit(salt)), F.lit(blocks)).cast("int")
    over = lambda blocks: F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = coded.drop("q").withColumn("rb", block(row_blocks, 1)).withColumn("qb", over(query_blocks))
    right = coded.where("q").withColumn("qb", block(query_blocks, 2)).select(F.col("row").alias("q_row"), F.col("id").alias("q_id"), F.col("v").alias("q_v"), "qb").withColumn("rb", over(row_blocks))
    names, types = ["query_row", "query_id", "vec_id", "score"], (pa.int64(), pa.int64(), pa.int64(), pa.float64())

    def meet(x: pa.Table, q: pa.Table) -> pa.Table:
        mean, turn = held.value
        got: list[tuple] = []
        if min(x.num_rows, x.num_columns, q.num_rows, q.num_columns):  # a side without rows has no columns
            row, ids, q_row, q_id = (c.to_numpy() for c in (x.column("row"), x.column("id"), q.column("q_row"), q.column("q_id")))
            asked = _matrix(q.column("q_v"), d).astype(np.float64)
            codes = _words(x.column("code"), len(x))
            best = search_block(q_row, asked, row, ids, _matrix(x.column("v"), d), codes, x.column("length").to_numpy(), x.column("inner").to_numpy(), mean, turn, k, eps)
            got = [(q_row[i], q_id[i], ids[a], s) for i, a, s in best]
        return pa.table([pa.array(c, t) for c, t in zip(zip(*got, strict=True) if got else [[]] * 4, types, strict=True)], names=names)

    best = left.groupBy("rb", "qb").cogroup(right.groupBy("rb", "qb")).applyInArrow(meet, "query_row long, query_id long, vec_id long, score double")
    rank = F.row_number().over(Window.partitionBy("query_row").orderBy("score", "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
