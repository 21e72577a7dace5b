"""N-gram Jaccard join by chosen paths.

A document's set is the hashes of its runs of SHINGLE words (one run where it has fewer). Equal sets are
one record. Each record is embedded as one token for each of BINS ranges of the hashes, the least hash in
it, and each run draws a sequence of tokens of its own: the least hash of the whole set under an order that
only this draw has, so that two records share each draw with the probability of their Jaccard similarity,
however few shingles they have. Records that share the first draw of a run share a bucket, buckets above LEAF
records are split by the next draws, down to the last of LEVELS; small buckets are compared by brute force on
the embedding, with slack. The number of runs follows from the recall asked for. What is still large at the
last level is kept together as it is. The links found only say which records belong in one candidate class.

Candidate classes are then joined exactly, on whole sets: a class is one group, or, if it is large, one
group for each pair of its blocks. So every pair of a class is compared, and each group sends only the
number of links of each record and a spanning forest. Classes of the result are connected by exact links.

Null doc_ids take no part: class and links are null and 0. Texts without words link to nothing. Rows with
equal sets are linked to each other; so are repeated rows. An empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.llm import words as W
from factorclust.llm.shared import components, cut, free_name, tidy

SHINGLE, SIMILARITY = 5, 0.8
BINS, LEAF = 128, 96
#: Tokens chosen at each level of a run.
LEVELS = (1, 2)
#: Share of pairs at the threshold that the runs find, even where buckets are split down to the last level.
RECALL = 0.998
#: How far below the threshold the embedding may estimate a pair: some five standard errors of BINS draws.
SLACK = 0.18
#: Records and shingles of a block of a large class.
BLOCK_RECORDS, BLOCK_SHINGLES = 192, 500_000
#: Shingles whose draws are made at once.
AT_ONCE = 4096


def runs_for(recall: float, similarity: float, depth: int) -> int:
    """Runs after which a pair at the threshold has met in the last level with this probability."""
    return math.ceil(math.log(1 - recall) / math.log(1 - similarity**depth))


def chosen_orders(runs: int, depth: int, seed: int = 11) -> np.ndarray:
    """A number for the order of each draw, runs by depth; no two draws share one."""
    return W.mix(np.arange(1, runs * depth + 1, dtype=np.uint64) + np.uint64(seed << 32)).reshape(runs, depth)


def shingle_sets(texts: pa.Array, k: int = SHINGLE) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text in turn."""
    for _, word, doc in W.whole(texts):
        h, _ = W.grams(word, doc, k)
        for lo, hi in zip(doc[:-1].tolist(), doc[1:].tolist(), strict=True):
            if hi - lo >= k:
                yield np.unique(h[lo : hi - k + 1])
            elif hi > lo:
                short, _ = W.grams(word[lo:hi], np.array([0, hi - lo]), hi - lo)
                yield W.mix(short[:1] + np.uint64(hi - lo))
            else:
                yield np.zeros(0, np.uint64)


def embed(u: np.ndarray, bins: int = BINS) -> np.ndarray:
    """The least hash in each range (its low 32 bits, 0 where the range is empty)."""
    if not len(u):
        return np.zeros(bins, np.uint32)
    shift = np.uint64(64 - int(bins).bit_length() + 1)
    edges = np.arange(bins, dtype=np.uint64) << shift
    at = np.searchsorted(u, edges)
    value = u[np.minimum(at, len(u) - 1)]
    have = (at < len(u)) & ((value >> shift) == np.arange(bins, dtype=np.uint64))
    return np.where(have, np.maximum(1, value & np.uint64(0xFFFFFFFF)), 0).astype(np.uint32)


def path_keys(u: np.ndarray, orders: np.ndarray, levels: tuple[int, ...] = LEVELS) -> np.ndarray:
    """Keys of the buckets of one record's shingle hashes, runs by LEVELS."""
    flat = orders.ravel()
    token = np.full(len(flat), np.iinfo(np.uint64).max)
    for lo in range(0, len(u), AT_ONCE):
        token = np.minimum(token, W.mix(u[lo : lo + AT_ONCE, None] ^ flat).min(0))
    token = token.reshape(orders.shape)
    keys = np.zeros((len(orders), len(levels)), np.uint64)
    key = W.mix(np.arange(1, len(orders) + 1, dtype=np.uint64))
    at = 0
    for level, n in enumerate(levels):
        for _ in range(n):
            key = W.mix(key * np.uint64(0x9E3779B97F4A7C15) + token[:, at])
            at += 1
        keys[:, level] = key
    return keys.view(np.int64)


def describe(rows: DataFrame, similarity: float = SIMILARITY, recall: float = RECALL) -> DataFrame:
    """(row, doc_id, text) -> row, doc_id, n shingles, set (a hash of the whole set), sketch, keys of its buckets by run and level."""
    orders = chosen_orders(runs_for(recall, similarity, sum(LEVELS)), sum(LEVELS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, ids, sketches, keys = [], [], [], []
            for u in shingle_sets(b.column(2)):
                n.append(len(u))
                ids.append(int(W.mix(np.array([W.mix(u).sum(), len(u)], np.uint64))[0].astype(np.int64)) if len(u) else 0)
                sketches.append(embed(u).tobytes() if len(u) else b"")
                keys.append(path_keys(u, orders).ravel() if len(u) else np.zeros(0, np.int64))
            ends = np.cumsum([0, *map(len, keys)])
            lists = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([*keys, np.zeros(0, np.int64)])))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(ids, pa.int64()), pa.array(sketches, pa.binary()), lists], names=["row", "doc_id", "n", "set", "sketch", "keys"])

    return rows.mapInArrow(tidy(run), "row long, doc_id long, n long, set long, sketch binary, keys array<long>")


def grouped(key: int, work: Callable[[pa.Table], Iterator[pa.RecordBatch]]):
    """For rows sorted by column ``key``: calls ``work`` with the whole groups of each batch, in one table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            if not b.num_rows:
                continue
            k = b.column(key).to_numpy(zero_copy_only=False)
            if held and held[-1].column(key)[-1].as_py() != k[0]:
                yield from work(pa.Table.from_batches(held))
                held = []
            at = int(np.searchsorted(-(k == k[-1]).astype(np.int8), -1, "left")) if k[0] == k[-1] else int(np.flatnonzero(k != k[-1])[-1]) + 1
            if at:
                held.append(b.slice(0, at))
                yield from work(pa.Table.from_batches(held))
                held = []
            held.append(b.slice(at))
        if held:
            yield from work(pa.Table.from_batches(held))

    return run


def _spans(k: np.ndarray) -> Iterator[tuple[int, int]]:
    edge = np.concatenate([[0], np.flatnonzero(k[1:] != k[:-1]) + 1, [len(k)]])
    return zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)


def roots(near: np.ndarray) -> np.ndarray:
    """For each record the first record it is connected with."""
    n = len(near)
    root = np.full(n, -1)
    for i in range(n):
        if root[i] >= 0:
            continue
        front = [i]
        root[i] = i
        while front:
            new = np.flatnonzero(near[front].any(0) & (root < 0))
            root[new] = i
            front = new.tolist()
    return root


def brute_force_buckets(table: pa.Table, least: float) -> Iterator[pa.RecordBatch]:
    """(path, set, sketch) by path -> links (a, b) that connect whatever the embedding puts above ``least``."""
    key, sets, raw = table.column(0).to_numpy(), table.column(1).to_numpy(), table.column(2).to_pylist()
    a: list[np.ndarray] = []
    b: list[np.ndarray] = []
    for lo, hi in _spans(key):
        sk = np.frombuffer(b"".join(raw[lo:hi]), np.uint32).reshape(hi - lo, -1)
        same = ((sk[:, None, :] == sk[None, :, :]) & (sk[:, None, :] != 0)).sum(2)
        either = ((sk[:, None, :] != 0) | (sk[None, :, :] != 0)).sum(2)
        root = roots(same >= least * either)
        other = root != np.arange(hi - lo)
        a.append(sets[lo:hi][other])
        b.append(sets[lo:hi][root[other]])
    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(a), pa.int64()), pa.array(np.concatenate(b), pa.int64())], names=["a", "b"])


def intersections(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairwise intersections. Shingles that lie in the same records count together."""
    n = len(sets)
    size = [len(s) for s in sets]
    owner = np.repeat(np.arange(n), size)
    _, which = np.unique(np.concatenate(sets), return_inverse=True)
    sign = W.mix(np.arange(1, n + 1, dtype=np.uint64))
    pattern = np.zeros(int(which.max()) + 1 if len(which) else 0, np.uint64)
    np.add.at(pattern, which, sign[owner])
    _, first, column, weight = np.unique(pattern, return_index=True, return_inverse=True, return_counts=True)
    chosen = np.zeros(len(pattern), bool)
    chosen[first] = True
    mine = chosen[which]
    row, col = owner[mine], column[which[mine]]
    order = np.argsort(col, kind="stable")
    row, col = row[order], col[order]
    out = np.zeros((n, n))
    for lo in range(0, len(weight), 4096):
        s, e = np.searchsorted(col, [lo, lo + 4096])
        m = np.zeros((n, min(4096, len(weight) - lo)), np.float32)
        m[row[s:e], col[s:e] - lo] = 1
        out += (m * weight[lo : lo + 4096].astype(np.float32)) @ m.T
    return out


def exact_links(table: pa.Table, similarity: float, k: int) -> Iterator[pa.RecordBatch]:
    """(group, block, cross, set, copies, text) by group -> (set, links, root): documents linked within the group."""
    key = table.column(0).to_numpy()
    block, cross, sets, copies = (table.column(i).to_numpy() for i in range(1, 5))
    texts = table.column(5).combine_chunks()
    for lo, hi in _spans(key):
        _, at = np.unique(sets[lo:hi], return_index=True)  # a repeated row brings its text twice
        at = np.sort(at) + lo
        shingles = list(shingle_sets(texts.take(pa.array(at)), k))
        n = np.array([len(s) for s in shingles])
        inter = intersections(shingles)
        near = inter >= similarity * (n[:, None] + n[None, :] - inter) - 1e-9
        np.fill_diagonal(near, False)
        if cross[lo]:
            near &= block[at][:, None] != block[at][None, :]
        links = near @ copies[at]
        root = roots(near)
        yield pa.RecordBatch.from_arrays([pa.array(sets[at], pa.int64()), pa.array(links, pa.int64()), pa.array(sets[at][root], pa.int64())], names=["set", "links", "root"])


def candidates(records: DataFrame, similarity: float = SIMILARITY, recall: float = RECALL, leaf: int = LEAF) -> DataFrame:
    """(a, b) links that connect each candidate class of the records (set, sketch, keys)."""
    runs, depth = runs_for(recall, similarity, sum(LEVELS)), len(LEVELS)
    keyed = records.select("set", "keys")
    every = F.explode(F.sequence(F.lit(0), F.lit(runs - 1)))
    nodes = keyed.withColumn("run", every).select("set", "run", F.element_at("keys", F.col("run") * depth + 1).alias("path"))
    leaves: DataFrame | None = None
    links: DataFrame | None = None
    for level in range(depth):
        sizes = nodes.groupBy("path").agg(F.count(F.lit(1)).alias("n"), *[F.bit_xor(F.xxhash64("set", F.lit(i))).alias(f"sign{i}") for i in (0, 1)]).where("n > 1")
        sizes = cut(sizes, "buckets")
        small = sizes.where(F.col("n") <= leaf).groupBy("n", "sign0", "sign1").agg(F.min("path").alias("path")).select("path")  # the same records, told by 128 bits, met in many runs, are compared once
        found = nodes.join(small, "path").select("path", "set")
        leaves = found if leaves is None else leaves.unionByName(found)
        large = sizes.where(F.col("n") > leaf).select("path")
        if large.isEmpty():
            break
        rest = cut(nodes.join(large, "path"), "large")
        if level + 1 < depth:
            nodes = rest.select("set", "run").join(keyed, "set").select("set", "run", F.element_at("keys", F.col("run") * depth + level + 2).alias("path"))
        else:
            ends = rest.groupBy("path").agg(F.min("set").alias("b"))
            links = rest.join(ends, "path").select(F.col("set").alias("a"), "b").distinct()
    least = similarity - SLACK
    pairs = leaves.join(records.select("set", "sketch"), "set").select("path", "set", "sketch").repartition("path").sortWithinPartitions("path").mapInArrow(tidy(grouped(0, lambda t: brute_force_buckets(t, least))), "a long, b long")
    return pairs if links is None else pairs.unionByName(links)


def classes(rows: DataFrame, similarity: float = SIMILARITY, k: int = SHINGLE) -> DataFrame:
    """(row, doc_id, text) -> row, doc_id, class_id (its least doc_id), n_links (other documents at the threshold), n_shingles."""
    told = cut(describe(rows, similarity), "sets")
    some = told.where("doc_id is not null and n > 0")
    records = cut(some.groupBy("set", "n", "sketch", "keys").agg(F.min("row").alias("row"), F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("copies")), "records")
    cand = cut(components(candidates(records, similarity)), "candidates")
    size = cand.join(records.select(F.col("set").alias("node"), "n", "row", "copies"), "node")
    blocks = size.groupBy("comp").agg(F.ceil(F.greatest(F.count(F.lit(1)) / BLOCK_RECORDS, F.sum("n") / BLOCK_SHINGLES)).cast("int").alias("blocks"))
    member = size.join(blocks, "comp").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    # always shuffled: were few candidates broadcast, small inputs would have another plan than large ones
    texts = rows.select(F.col("row"), "text").hint("merge").join(member, "row")
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    met = texts.withColumn("other", other).select(
        F.xxhash64("comp", F.least("block", "other"), F.greatest("block", "other")).alias("group"), "block", (F.col("block") != F.col("other")).alias("cross"), F.col("node").alias("set"), "copies", "text",
    )
    # the group of a pair of blocks holds both blocks; rows of either name it
    exact = cut(met.repartition("group").sortWithinPartitions("group", "set").mapInArrow(tidy(grouped(0, lambda t: exact_links(t, similarity, k))), "set long, links long, root long"), "links")
    linked = exact.groupBy("set").agg(F.sum("links").alias("links"))
    joined = components(exact.select(F.col("set").alias("a"), F.col("root").alias("b"))).withColumnRenamed("node", "set")
    whole = records.select("set", "least", "copies").join(linked, "set", "left").join(joined, "set", "left").withColumn("comp", F.coalesce("comp", "set"))
    first = whole.groupBy("comp").agg(F.min("least").alias("class_id"))
    of_set = whole.join(first, "comp").select("set", "class_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    plain = told.select("row", "doc_id", "n", F.when(F.col("doc_id").isNotNull() & (F.col("n") > 0), F.col("set")).alias("set"))
    return plain.join(of_set, "set", "left").select("row", "doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).alias("n_links"), F.col("n").alias("n_shingles"))


def _rows(documents: DataFrame) -> DataFrame:
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.select(F.xxhash64("doc_id", "text").alias("row"), "doc_id", "text")


def join(documents: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    return classes(_rows(documents), similarity).drop("row")


def keep_first(documents: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """One document of each class, the one with the least doc_id, with all its columns; rows with null doc_ids all stay."""
    found = cut(classes(_rows(documents), similarity), "classes")
    name = free_name(documents.columns, "row")
    keep = found.where(F.col("doc_id") == F.col("class_id")).groupBy("class_id").agg(F.min("row").alias(name)).select(name)
    key = F.xxhash64(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    kept = documents.where(F.col("doc_id").isNotNull()).withColumn(name, key).hint("merge").join(keep, name, "left_semi")
    columns = [F.col(f"`{c}`") for c in documents.columns]
    return kept.dropDuplicates([name]).select(*columns).unionByName(documents.where(F.col("doc_id").isNull()))
