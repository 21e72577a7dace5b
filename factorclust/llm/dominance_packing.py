"""Best-fit packing of token pieces into sequences, after a dominance reduction of the instance.

Token counts are whole numbers up to the length of a sequence, so any corpus is an instance of at most
``room`` distinct sizes with counts. The reduction fixes sets that hold the largest open size and provably
dominate every other set with it; best fit with falling sizes places the remainder. Both work on whole
runs of equal bins, so the plan has a few rows for each distinct size, however many documents there are (a
choice of the reduction is repeated until a count falls so low that it may change);
the documents are then matched to the plan by their number among the pieces of their size.

A null or empty text has its end id alone. Documents above ``room`` tokens are cut; the piece that takes
the odd rest comes first. Repeated rows are packed each by itself. An empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.llm.shared import cut, gapless, tidy
from factorclust.llm.tokens import encoder

ROOM = 2048
#: Pieces of a size beyond which one more changes no choice of the reduction.
STEADY = 4


@dataclass
class Run:
    """``bins`` bins with the same content: numbers first..first+bins-1, ``used`` tokens each."""

    first: int
    bins: int
    used: int


@dataclass
class Plan:
    """Rows (size, from, bins, first bin, offset, rounds): pieces number from.. of this size fill the bins of
    a run ``rounds`` deep, one beside the other from ``offset`` on."""

    room: int
    rows: list[tuple[int, int, int, int, int, int]] = field(default_factory=list)
    bins: int = 0
    fixed_bins: int = 0
    lower_bound: int = 0
    taken: dict[int, int] = field(default_factory=dict)

    def open(self, n: int) -> Run:
        run = Run(self.bins, n, 0)
        self.bins += n
        return run

    def put(self, size: int, run: Run, rounds: int = 1) -> None:
        """The next pieces of this size go into all bins of the run."""
        at = self.taken.get(size, 0)
        self.rows.append((size, at, run.bins, run.first, run.used, rounds))
        self.taken[size] = at + run.bins * rounds
        run.used += size * rounds


def _largest_at_most(left: np.ndarray) -> np.ndarray:
    """For each number up to room the largest open size that isn't above it, or 0."""
    sizes = np.arange(len(left))
    return np.maximum.accumulate(np.where(left > 0, sizes, 0))


def _smallest(left: np.ndarray, n: int) -> list[int]:
    """The n smallest open pieces, with their multiplicity."""
    out: list[int] = []
    for size in np.flatnonzero(left)[:n]:
        out += [int(size)] * int(min(n, left[size]))
    return out[:n]


def dominating(left: np.ndarray, size: int, room: int) -> tuple[int, ...] | None:
    """What to put beside one piece of ``size``, taken from ``left`` (without it), if provably no choice is better.

    A set beats another if each piece of the other can be exchanged for a piece of its own that is at least
    as large, several for one where their sum isn't larger. Of a size with many pieces only the first three count.
    """
    rest = room - size
    below = _largest_at_most(left)
    best = int(below[rest])
    if best == 0:
        return ()
    if best == rest:
        return (best,)  # whatever else fits has at most this sum
    two = _smallest(left, 2)
    if len(two) < 2 or sum(two) > rest:
        return (best,)  # only single pieces fit, and this is the largest
    three = _smallest(left, 3)
    if len(three) == 3 and sum(three) <= rest:
        return None
    # at most two more pieces fit
    open_sizes = np.flatnonzero(left[: rest + 1])
    others = left.copy()
    partner = np.zeros(len(open_sizes), np.int64)
    fits = rest - open_sizes
    partner = below[fits]
    alone = (partner == open_sizes) & (left[open_sizes] == 1)  # no second piece of this size
    for i in np.flatnonzero(alone):
        others[open_sizes[i]] = 0
        partner[i] = _largest_at_most(others)[fits[i]]
        others[open_sizes[i]] = left[open_sizes[i]]
    sums = np.where(partner > 0, open_sizes + partner, 0)
    if sums.max(initial=0) <= best:
        return (best,)  # any pair can be exchanged for this one piece
    others[best] -= 1
    second = int(_largest_at_most(others)[rest - best])
    if not second:
        return None
    # (best, second) beats every pair (x, y), y <= x, with y <= second; is there one with both above?
    above = left.copy()
    above[: second + 1] = 0
    pair = _smallest(above, 2)
    return (best, second) if len(pair) < 2 or sum(pair) > rest else None


def reduce_instance(counts: np.ndarray, plan: Plan) -> np.ndarray:
    """Fixes dominating sets for good, largest sizes first, until a pass changes nothing; returns what is left."""
    room, left = plan.room, counts.copy()
    changed = True
    while changed:
        changed = False
        for size in np.flatnonzero(left)[::-1]:
            size = int(size)
            while left[size]:
                left[size] -= 1
                beside = dominating(left, size, room)
                left[size] += 1
                if beside is None:
                    break
                need: dict[int, int] = {size: 1}
                for x in beside:
                    need[x] = need.get(x, 0) + 1
                # the choice depends on counts up to STEADY only, so it holds while those taken from stay as many
                times = max(1, min((int(left[x]) - STEADY) // n for x, n in need.items()))
                if not beside or size + beside[0] == room:  # these stay right to the last piece
                    times = min(int(left[x]) // n for x, n in need.items())
                run = plan.open(times)
                for x in (size, *beside):
                    plan.put(x, run)
                    left[x] -= times
                changed = True
    plan.fixed_bins = plan.bins
    return left


def best_fit(left: np.ndarray, plan: Plan) -> None:
    """Falling sizes, each into the fullest bins that still take it; whole runs of equal bins at once."""
    room = plan.room
    by_free: dict[int, list[Run]] = {}
    for size in np.flatnonzero(left)[::-1]:
        size, n = int(size), int(left[size])
        while n:
            free = min((f for f in by_free if f >= size), default=None)
            if free is None:
                deep = room // size
                bins = n // deep
                run, rounds = (plan.open(bins), deep) if bins else (plan.open(1), n)
            else:
                run = by_free[free].pop()
                if not by_free[free]:
                    del by_free[free]
                rounds = free // size
                bins = n // rounds
                if bins == 0:
                    bins, rounds = 1, n
                if bins < run.bins:
                    by_free.setdefault(free, []).append(Run(run.first + bins, run.bins - bins, run.used))
                    run = Run(run.first, bins, run.used)
            plan.put(size, run, rounds)
            n -= run.bins * rounds
            if room - run.used:
                by_free.setdefault(room - run.used, []).append(run)


def make_plan(counts: dict[int, int], room: int = ROOM) -> Plan:
    """The plan for pieces of the sizes and counts given; its size depends on ``room`` only."""
    if any(not 1 <= s <= room for s in counts):
        raise ValueError(f"sizes must lie in 1..{room}")
    have = np.zeros(room + 1, np.int64)
    for s, n in counts.items():
        have[s] = n
    plan = Plan(room)
    plan.lower_bound = int(-(-int((np.arange(room + 1) * have).sum()) // room))
    best_fit(reduce_instance(have, plan), plan)
    return plan


def pieces(documents: DataFrame, tokenizer: str, room: int = ROOM, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece of every document, and its ids if asked for; one narrow pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code = encoder(tokenizer)
        for batch in batches:
            rows: list[tuple] = []
            for doc, ids in zip(batch.column(0).to_pylist(), code.encode_many(batch.column(1).to_pylist()), strict=True):
                ids = ids.astype("<u4")
                at = 0
                for k in range(-(-len(ids) // room)):
                    to = len(ids) % room or room if k == 0 else at + room
                    rows.append((doc, k, at, to - at, zlib.crc32(ids[at:to].tobytes()), *([ids[at:to].astype(np.int32)] if with_ids else [])))
                    at = to
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * len(types), types, strict=True)], names=names)

    types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), *([pa.list_(pa.int32())] if with_ids else []))
    names = ["doc_id", "piece", "start", "length", "ids_crc32", *(["ids"] if with_ids else [])]
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "")
    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(tidy(run), schema)


def pack(documents: DataFrame, tokenizer: str, room: int = ROOM, with_ids: bool = False) -> DataFrame:
    """Pieces with sequence_id (from 0) and offset (gapless from 0 in a sequence), and their ids if asked for."""
    spark = documents.sparkSession
    cuts = cut(pieces(documents, tokenizer, room, with_ids), "pieces")
    counts = {r.length: r.n for r in cuts.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # room rows at most
    plan = make_plan(counts, room)
    steps = spark.createDataFrame(plan.rows or [(0, 0, 0, 0, 0, 1)], "p_size long, p_from long, p_bins long, p_first long, p_offset long, p_rounds long")
    numbered = gapless(cuts, ["length"], ["doc_id", "piece", "ids_crc32"], "nth")
    inside = (F.col("length") == F.col("p_size")) & (F.col("nth") >= F.col("p_from")) & (F.col("nth") < F.col("p_from") + F.col("p_bins") * F.col("p_rounds"))
    at = F.col("nth") - F.col("p_from")
    bins = F.greatest(F.col("p_bins"), F.lit(1))
    return numbered.join(F.broadcast(steps), inside).select(
        *cuts.columns,
        (F.col("p_first") + at % bins).alias("sequence_id"),
        (F.col("p_offset") + F.floor(at / bins).cast("long") * F.col("length")).alias("offset"),
    )


def sequences(packed: DataFrame) -> DataFrame:
    """sequence_id, ids (all its pieces, in place), starts (where each piece begins) of pieces packed with their ids; a group has ``room`` ids at most."""
    one = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("all"))
    return one.select("sequence_id", F.flatten(F.transform("all", lambda p: p["ids"])).alias("ids"), F.transform("all", lambda p: p["offset"]).alias("starts"))
