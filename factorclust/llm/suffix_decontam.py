"""Benchmark decontamination by suffix arrays of the training words.

Each task gathers its documents into shards of about SHARD words, whole documents each, and sorts the shard's
suffixes by their first words. Every suffix of every benchmark item is then searched for by bisection; the range
that shares its whole window gives all places of that window, and each place is followed as far as it goes, for
the longest verbatim match. Suffixes of either side whose first two words the other side has nowhere in a row
cannot share a window: those of the shard are left out before the sort, those of the benchmark, which are kept
in order of their first two words, before the search. Documents never move: there is no shuffle.

The benchmark is cut into blocks of about BLOCK words by a hash of its items. A scan of the documents takes one
block, as one broadcast; a benchmark of several blocks takes as many scans, whose hits are put together by
document at the end. So what a task holds is bounded, whatever the size of the benchmark.

A window has ``window`` words; an item of fewer, but not none, is one window. Null or empty texts have no
words and no hits; repeated rows each get their own row; repeated items count by their item_id once; items
without words are passed over; an empty benchmark hits nothing. Only the columns named are read, so extra
columns cannot clash.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.llm import words as W
from factorclust.llm.shared import cut, free_name, tidy

WINDOW = 13
#: Words of a shard; it ends with the document that reaches them.
SHARD = 1 << 18
#: Words of a block of the benchmark, one broadcast.
BLOCK = 4_000_000


@dataclass
class Probes:
    """The windows of one length: where they begin in Items.text, their items, and their order by first two words."""

    length: int
    at: np.ndarray
    item: np.ndarray
    pair: np.ndarray  # sorted keys of the first two words (of one, where the length is 1)


@dataclass
class Items:
    """A block of the benchmark: hashes of its words with a 0 after each item, where items begin, their ids as strings."""

    text: np.ndarray
    begin: np.ndarray
    ids: list[str]
    probes: list[Probes] = field(default_factory=list)

    @staticmethod
    def of(words: list[np.ndarray], ids: list[str], window: int) -> Items:
        """With the windows of all items; made once, on the driver, and broadcast as it is."""
        zero = np.zeros(1, np.uint64)
        size = np.array([len(w) for w in words], np.int64)
        text = np.concatenate([x for w in words for x in (w, zero)] + [zero])
        begin = np.concatenate([[0], np.cumsum(size + 1)[:-1]]).astype(np.int64) if len(words) else np.zeros(0, np.int64)
        items = Items(text, begin, ids)
        after = pair_keys(text)
        for length in np.unique(np.minimum(size, window)):
            if length == 0:
                continue
            mine = np.flatnonzero(size >= window) if length == window else np.flatnonzero(size == length)
            n = size[mine] - length + 1
            at = np.repeat(begin[mine], n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
            key = text[at] if length == 1 else after[at]
            order = np.argsort(key, kind="stable")
            items.probes.append(Probes(int(length), at[order], np.repeat(mine, n)[order], key[order]))
        return items


def pair_keys(text: np.ndarray) -> np.ndarray:
    """A key of each word and the one after it."""
    return W.mix(text * np.uint64(3) ^ np.concatenate([text[1:], np.zeros(1, text.dtype)]))


def _search(text: np.ndarray, order: np.ndarray, probe: np.ndarray, starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """For each probe suffix probe[s:s+length] the range of ``order`` whose suffixes begin with it."""
    ends = []
    for after in (False, True):
        lo, hi = np.zeros(len(starts), np.int64), np.full(len(starts), len(order), np.int64)
        while (open_ := lo < hi).any():
            mid = (lo + hi) // 2
            at = order[np.minimum(mid, len(order) - 1)]
            less, equal = np.zeros(len(starts), bool), np.ones(len(starts), bool)
            for i in range(length):
                where = at + i
                have = np.where(where < len(text), text[np.minimum(where, len(text) - 1)], 0)
                want = probe[starts + i]
                less |= equal & (have < want)
                equal &= have == want
            right = (less | (equal & after)) & open_
            lo = np.where(right, mid + 1, lo)
            hi = np.where(open_ & ~right, mid, hi)
        ends.append(lo)
    return ends[0], ends[1]


def suffix_array(text: np.ndarray, at: np.ndarray, depth: int) -> np.ndarray:
    """The positions ``at`` in the order of the suffixes' first ``depth`` words (0 ends a document)."""
    padded = np.concatenate([text, np.zeros(depth, text.dtype)])
    return at[np.lexsort([padded[at + i] for i in range(depth - 1, -1, -1)])]


def _longest(text: np.ndarray, probe: np.ndarray, at: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    run = np.full(len(at), length, np.int64)
    open_ = np.arange(len(at))
    while len(open_):
        a, b = at[open_] + run[open_], starts[open_] + run[open_]
        same = (a < len(text)) & (b < len(probe))
        same[same] = (text[a[same]] == probe[b[same]]) & (text[a[same]] != 0)
        open_ = open_[same]
        run[open_] += 1
    return run


def search_shard(text: np.ndarray, items: Items) -> tuple[np.ndarray, ...]:
    """(place, item number, place in the item, window length, run) of every window in text; words 0 part documents."""
    out: list[tuple[np.ndarray, ...]] = []
    pairs = pair_keys(text)
    for p in items.probes:
        have = text if p.length == 1 else pairs
        at = np.minimum(np.searchsorted(p.pair, have), len(p.pair) - 1)
        some = np.flatnonzero((p.pair[at] == have) & (text != 0))
        if not len(some):
            continue
        order = suffix_array(text, some, p.length)
        # the suffixes of the benchmark that begin with two words of these
        keys = np.unique(have[some])
        first, last = np.searchsorted(p.pair, keys, "left"), np.searchsorted(p.pair, keys, "right")
        n = last - first
        asked = np.repeat(first, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        starts, owner = p.at[asked], p.item[asked]
        lo, hi = _search(text, order, items.text, starts, p.length)
        n = hi - lo
        if not n.sum():
            continue
        which = np.repeat(np.arange(len(starts)), n)
        at = order[np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)]
        run = _longest(text, items.text, at, starts[which], p.length)
        out.append((at, owner[which], starts[which] - items.begin[owner[which]], np.full(len(at), p.length), run))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else tuple(np.zeros(0, np.int64) for _ in range(5))


def _shards(texts: pa.Array) -> Iterator[tuple[np.ndarray, list[tuple[int, int, int]]]]:
    """(words with a 0 after each document, documents (row, place here, words))."""
    held: list[np.ndarray] = []
    rows: list[tuple[int, int, int]] = []
    size = 0
    zero = np.zeros(1, np.uint64)
    for first, word, doc in W.whole(texts):
        for k, (lo, hi) in enumerate(zip(doc[:-1].tolist(), doc[1:].tolist(), strict=True)):
            held += [word[lo:hi], zero]
            rows.append((first + k, size, hi - lo))
            size += hi - lo + 1
            if size >= SHARD:
                yield np.concatenate(held), rows
                held, rows, size = [], [], 0
    if rows:
        yield np.concatenate(held), rows


def scan(texts: pa.Array, items: Items) -> tuple[np.ndarray, dict[int, np.ndarray], dict[int, dict[int, tuple[int, int, int]]]]:
    """(words of each text, {text: hit words}, {text: {item: (longest match, its place, its place in the item)}})."""
    count = np.zeros(len(texts), np.int64)
    hit: dict[int, np.ndarray] = {}
    best: dict[int, dict[int, tuple[int, int, int]]] = {}
    for text, rows in _shards(texts):
        begin = np.array([r[1] for r in rows])
        for row, _, m in rows:
            count[row] = m
        at, item, item_at, size, run = search_shard(text, items)
        owner = np.searchsorted(begin, at, "right") - 1
        for k in np.unique(owner):
            row, place, _ = rows[k]
            mine = owner == k
            a, s = at[mine] - place, size[mine]
            hit[row] = np.unique(np.repeat(a, s) + np.arange(s.sum()) - np.repeat(np.cumsum(s) - s, s))
            seen = best.setdefault(row, {})
            i, ia, r = item[mine], item_at[mine], run[mine]
            for j in np.lexsort([ia, a, -r, i]):
                seen.setdefault(int(i[j]), (int(r[j]), int(a[j]), int(ia[j])))
    return count, hit, best


_LONGEST = pa.list_(pa.struct([("item_id", pa.string()), ("words", pa.int64()), ("doc_word", pa.int64()), ("item_word", pa.int64())]))
_FOUND = "n_words long, hits array<long>, longest array<struct<item_id:string,words:long,doc_word:long,item_word:long>>"


def load_items(benchmark: DataFrame, window: int = WINDOW) -> Iterator[Items]:
    """The benchmark's items in blocks of about BLOCK words, one after the other; at least one block, if need be without items."""
    if not 1 <= window:
        raise ValueError("a window has at least one word")
    text = F.col("text").cast("string")
    rows = benchmark.select(F.col("item_id").cast("string").alias("item_id"), text.alias("text")).where("text is not null and item_id is not null").distinct()
    # a word takes a byte and, but for the last, a gap: half the bytes bound the words
    size = rows.agg(F.sum(F.octet_length("text") + 1).alias("bytes")).first().bytes or 0
    blocks = max(1, -(-size // (2 * BLOCK)))
    dealt = cut(rows.withColumn("block", F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks))), "items") if blocks > 1 else rows.withColumn("block", F.lit(0))
    for k in range(blocks):
        words, ids = [], []
        for r in dealt.where(F.col("block") == k).toLocalIterator():
            h = W.hash_one(W.split_words(r.text.encode()))
            if len(h):
                words.append(h)
                ids.append(r.item_id)
        yield Items.of(words, ids, window)


def _found(texts: pa.Array, items: Items) -> list[pa.Array]:
    """The columns of _FOUND."""
    count, hit, best = scan(texts, items)
    n = len(count)
    none = np.zeros(0, np.int64)
    hits = [hit.get(i, none) for i in range(n)]
    ends = np.concatenate([[0], np.cumsum([len(h) for h in hits])]).astype(np.int32)
    long = []
    for i in range(n):
        named: dict[str, tuple[int, int, int]] = {}
        for j, x in best.get(i, {}).items():  # texts of one item_id count as one item
            if items.ids[j] not in named or named[items.ids[j]][0] < x[0]:
                named[items.ids[j]] = x
        long.append([{"item_id": k, "words": r, "doc_word": a, "item_word": b} for k, (r, a, b) in sorted(named.items())])
    return [pa.array(count), pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*hits, none]))), pa.array(long, _LONGEST)]


def matches(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, hits (word numbers), items (sorted), longest (the longest match with each item)."""
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    blocks = load_items(benchmark, window)
    first, more = next(blocks), next(blocks, None)
    found = _scanned(rows, first) if more is None else _in_passes(rows, itertools.chain([first, more], blocks))
    return found.select("doc_id", "n_words", "hits", F.transform("longest", lambda x: x["item_id"]).alias("items"), "longest")


def _scanned(rows: DataFrame, items: Items) -> DataFrame:
    """The columns of ``rows`` but the last, the text, and those of _FOUND for one block of the benchmark."""
    held = rows.sparkSession.sparkContext.broadcast(items)
    kept = list(rows.schema)[:-1]
    names = [f.name for f in kept] + ["n_words", "hits", "longest"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays(batch.columns[:-1] + _found(batch.column(batch.num_columns - 1), held.value), names=names)

    return rows.mapInArrow(tidy(run), ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), _FOUND]))


def _in_passes(rows: DataFrame, blocks: Iterable[Items]) -> DataFrame:
    """(doc_id, text) -> doc_id and the columns of _FOUND: a scan for each block, of which the hits alone are kept, put
    together by the text they are in."""
    texts = rows.select(F.xxhash64("text").alias("key"), "text")
    parts = [cut(_scanned(texts, b).where(F.size("hits") > 0).dropDuplicates(["key"]), "hits") for b in blocks]
    longest_first = F.array_sort(F.flatten(F.collect_list(F.transform("longest", lambda x: F.struct(x["item_id"], -x["words"], x["doc_word"], x["item_word"])))))
    joined = reduce(DataFrame.unionByName, parts).groupBy("key").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("hits")))).alias("hits"), longest_first.alias("all"))
    one_each = F.filter("all", lambda x, i: (i == 0) | (F.get("all", i - 1)["item_id"] != x["item_id"]))
    longest = F.transform(one_each, lambda x: F.struct(x["item_id"].alias("item_id"), (-x["col2"]).alias("words"), x["doc_word"].alias("doc_word"), x["item_word"].alias("item_word")))
    joined = joined.select("key", F.col("hits").alias("some"), longest.alias("long"))
    counted = _scanned(rows.select("doc_id", F.xxhash64("text").alias("key"), "text"), Items.of([], [], WINDOW))
    return counted.join(joined, "key", "left").select("doc_id", "n_words", F.coalesce("some", "hits").alias("hits"), F.coalesce("long", "longest").alias("longest"))


def report(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20) -> DataFrame:
    """One row a document; contaminated where at least one word in ``share`` is hit."""
    found = matches(documents, benchmark, window)
    n_hit = F.size("hits").cast("long")
    return found.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        ((n_hit > 0) & (n_hit * share >= F.col("n_words"))).alias("contaminated"),
        F.coalesce(F.array_max(F.transform("longest", lambda x: x["words"])), F.lit(0)).alias("longest_match"), "longest",
    )


def decontaminate(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: int = 20) -> DataFrame:
    """The documents that aren't contaminated, with all their columns.

    The verdict is a function of the text: with one block of the benchmark it is found beside the row, with no
    join back; with more the texts hit too often, by hash, are joined out.
    """
    at = documents.columns.index("text")
    blocks = load_items(benchmark, window)
    first, more = next(blocks), next(blocks, None)
    if more is not None:
        key, text = free_name(documents.columns, "text_hash"), F.col("text").cast("string")
        hashed = documents.select(F.xxhash64(text).alias("doc_id"), text.alias("text"))
        found = _in_passes(hashed, itertools.chain([first, more], blocks))
        gone = found.where((F.size("hits") > 0) & (F.size("hits") * share >= F.col("n_words"))).select(F.col("doc_id").alias(key)).distinct()
        return documents.withColumn(key, F.xxhash64(text)).join(gone, key, "left_anti").select(*[F.col(f"`{c}`") for c in documents.columns])
    held = documents.sparkSession.sparkContext.broadcast(first)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            count, hit, _ = scan(batch.column(at), held.value)
            keep = np.ones(batch.num_rows, bool)
            for row, h in hit.items():
                keep[row] = share * len(h) < count[row]
            yield batch.filter(pa.array(keep))

    return documents.mapInArrow(tidy(run), documents.schema)
