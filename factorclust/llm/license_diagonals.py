"""License scans by diagonal voting.

The rolling hashes of k words of all documents are joined to the places where the templates have them. A
template that stands in a document gives votes with one difference of places, its diagonal; inserted or
missing words move it, so neighbouring diagonals are merged: votes are counted in bands of BAND diagonals, each
half over the next one, so votes that drift by no more than half a band lie in one band whole. Bands with
enough votes are verified on the words: the score of a place is 1 less the words to insert, drop or change for
each word of the template. Templates without tolerance (the base phrases) must stand word for word.

Words are counted in a narrow scan; only documents with votes enough are read again, and their texts move only if
they are too many for a broadcast of their keys. Null and empty texts have no words and no labels. Repeated
rows get the same result each. Templates are a parameter of at most MOST_WORDS words in all, so their table may
be broadcast. Extra columns aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from factorclust.llm import words as W
from factorclust.llm.shared import cut, tidy

#: Words of a rolling hash; diagonals of a band; share of votes and of words a notice needs.
GRAM, BAND, VOTES, SHARE = 2, 32, 0.5, 0.8
MOST_WORDS = 100_000
#: Grams of a template; longer ones are given in pieces with one label.
LONGEST = 62
#: Bands up to which they are broadcast to the scan of the texts (some 32 MB); more are shuffled.
BROADCAST_BANDS = 1_000_000


@dataclass(frozen=True)
class Template:
    label: str
    text: str
    base: bool = False  # word for word, counted by places


#: Phrases of well-known licences, and the labels they stand for.
TEMPLATES = (
    Template("mit", "mit license", True),
    Template("apache", "apache license", True),
    Template("gpl", "general public license", True),
    Template("mit-notice", "released under the mit license"),
    Template("mit-notice", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    Template("apache-2.0-notice", "licensed under the apache license version 2.0"),
    Template("gpl-3.0-notice", "this work is licensed under the gnu general public license version 3"),
    Template("cc-by-nc-4.0", "licensed under cc by nc 4.0"),
    Template("all-rights-reserved", "all rights reserved"),
    Template("bsd-notice", "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
)


def _grams(documents: DataFrame, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = b.column(0)
            held: list[np.ndarray] = []
            tail = np.zeros(0, np.uint64)
            done = 0
            for c in W.chunks(b.column(1)):
                word = np.concatenate([tail, c.word])
                doc = np.concatenate([[0], c.doc[1:] + len(tail)])
                h, ok = W.grams(word, doc, k)
                tail = np.zeros(0, np.uint64)
                if c.more:  # the grams that reach into the next chunk come with it
                    held.append(h[ok])
                    tail = word[len(word) - (k - 1) :] if k > 1 else tail
                    continue
                n = len(doc) - 1
                sizes = np.maximum(0, np.diff(doc) - k + 1)
                flat = h[ok]
                if held:
                    flat = np.concatenate([*held, flat])
                    sizes = np.array([len(flat)])
                    held = []
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(flat.view(np.int64)))
                yield pa.RecordBatch.from_arrays([keys.slice(done, n), lists], names=["key", "grams"])
                done += n

    return documents.mapInArrow(tidy(run), "key long, grams array<long>")


def best_place(have: list[bytes], want: list[bytes]) -> tuple[float, int, int]:
    """(score, first word, last word) of the place where a template stands best: the least words to insert, drop or
    change, for each word of the template; the earliest of equals."""
    n = len(want)
    text, whole = b" %b " % b" ".join(have), b" %b " % b" ".join(want)
    if (at := text.find(whole)) >= 0:  # word for word
        first = text.count(b" ", 0, at)
        return 1.0, first, first + n - 1
    number = {w: i for i, w in enumerate(dict.fromkeys(want))}
    wanted = np.array([number[w] for w in want])
    steps = np.arange(n + 1)
    cost, begin = steps.copy(), np.zeros(n + 1, np.int64)
    low, first, last = n, 0, -1
    for i, w in enumerate(have):
        other = wanted != number.get(w, -1)
        over = cost + 1  # a word too many
        over[0] = 0
        from_ = begin.copy()
        from_[0] = i + 1
        pair = cost[:-1] + other
        take = pair <= over[1:]
        step = over.copy()
        step[1:] = np.where(take, pair, over[1:])
        from_[1:] = np.where(take, begin[:-1], from_[1:])
        # words of the template that are missing: the least of step[j] + (later - j)
        lead = step - steps
        best = np.minimum.accumulate(lead)
        at = np.maximum.accumulate(np.where(lead == best, steps, 0))
        cost, begin = best + steps, from_[at]
        if cost[n] < low:
            low, first, last = int(cost[n]), int(begin[n]), i
    return 1 - low / n, first, last


def spans(documents: DataFrame, templates: Sequence[Template] = TEMPLATES, k: int = GRAM, vote_share: float = VOTES, share: float = SHARE) -> DataFrame:
    """doc, template (its number), label, base, first, last, score: all places of phrases, and for each other template
    and band with enough votes its best place; ``doc`` is a hash of doc_id and text, so of repeated rows one is searched."""
    spark = documents.sparkSession
    split = [W.split_words(t.text.encode()) for t in templates]
    if sum(map(len, split)) > MOST_WORDS or any(not k <= len(s) < LONGEST + k for s in split):
        raise ValueError(f"templates take {k} to {LONGEST + k - 1} words each and {MOST_WORDS} in all")
    places = []
    for t, s in enumerate(split):
        h, ok = W.grams(W.hash_one(s), np.array([0, len(s)]), k)
        places += [(int(x), t, j) for j, x in enumerate(h.view(np.int64)[ok].tolist())]
    needed = [len(s) - k + 1 if x.base else max(1, int(np.ceil(vote_share * (len(s) - k + 1)))) for x, s in zip(templates, split, strict=True)]
    where = F.broadcast(spark.createDataFrame(places, "gram long, template int, place int"))
    rows = _keyed(documents)
    hits = _grams(rows.select("key", "text"), k).select("key", F.posexplode("grams").alias("at", "gram")).join(where, "gram")
    of = lambda values: F.element_at(F.array(*[F.lit(v) for v in values]), F.col("template") + 1)
    diagonal, half = (F.col("at") - F.col("place")).cast("long"), BAND // 2
    band = F.floor(diagonal / half).cast("long") * half
    bands = F.when(of([t.base for t in templates]), F.array(diagonal)).otherwise(F.array(band - half, band))
    # a bit for each place of the template, so repeated rows don't vote twice
    votes = hits.select("key", "template", F.explode(bands).alias("band"), F.expr("shiftleft(1L, place)").alias("bit")).groupBy("key", "template", "band").agg(F.bit_or("bit").alias("bits"))
    enough = cut(votes.where(F.expr("bit_count(bits)") >= of(needed)).select("key", "template", "band"), "bands")

    few = enough.count() <= BROADCAST_BANDS
    by_doc = enough.groupBy("key").agg(F.array_sort(F.collect_list(F.struct("template", "band"))).alias("bands"))  # no more than a document's own words
    texts = rows.select("key", "text").join(F.broadcast(by_doc), "key") if few else rows.select("key", "text").hint("merge").join(by_doc, "key")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for key, text, bands in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                have = W.split_words((text or "").encode("utf-8", "surrogatepass"))
                seen: set[tuple] = set()
                for x in bands:
                    t, want = x["template"], split[x["template"]]
                    lo = max(0, x["band"])
                    if templates[t].base:
                        if have[lo : lo + len(want)] == want:
                            seen.add((t, lo, lo + len(want) - 1, 1.0))
                    else:
                        good, first, last = best_place(have[lo : x["band"] + BAND + len(want)], want)
                        if good >= share:
                            seen.add((t, lo + first, lo + last, good))
                out += [(key, t, templates[t].label, templates[t].base, first, last, good) for t, first, last, good in sorted(seen)]
            types = (pa.int64(), pa.int32(), pa.string(), pa.bool_(), pa.int64(), pa.int64(), pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 7, types, strict=True)], names=["doc", "template", "label", "base", "first", "last", "score"])

    found = texts.mapInArrow(tidy(verify), "doc long, template int, label string, base boolean, first long, last long, score double")
    return found.dropDuplicates(["doc", "template", "first", "last"])  # repeated rows, and bands that share a place


def _counted(rows: DataFrame) -> DataFrame:
    """(key, doc_id, text) -> key, doc_id, n_words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = np.zeros(b.num_rows, np.int64)
            for c in W.chunks(b.column(2)):
                n[c.first : c.first + len(c.doc) - 1] += np.diff(c.doc)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n)], names=["key", "doc_id", "n_words"])

    return rows.mapInArrow(tidy(run), "key long, doc_id long, n_words long")


def _keyed(documents: DataFrame) -> DataFrame:
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.select(F.xxhash64("doc_id", "text").alias("key"), "doc_id", "text")


def scan(documents: DataFrame, templates: Sequence[Template] = TEMPLATES, k: int = GRAM, vote_share: float = VOTES, share: float = SHARE) -> DataFrame:
    """One row a document: its words, the base phrases' places, the labels, and the best score."""
    found = spans(documents, templates, k, vote_share, share)
    base, names = F.col("base"), lambda c: F.array_join(F.array_sort(F.collect_set(c)), ",")
    by_doc = found.groupBy(F.col("doc").alias("key")).agg(
        F.count_if(base).alias("n_base"), F.min(F.when(base, F.col("first"))).alias("first_word"), F.max(F.when(base, F.col("first"))).alias("last_word"),
        names(F.when(base, F.col("label"))).alias("base_labels"), names(F.col("label")).alias("labels"), F.max("score").alias("score"),
    )
    return _counted(_keyed(documents)).join(by_doc, "key", "left").select(
        "doc_id", "n_words", F.coalesce("n_base", F.lit(0)).cast("long").alias("n_base"), "first_word", "last_word",
        *[F.coalesce(c, F.lit("")).alias(c) for c in ("base_labels", "labels")], F.coalesce("score", F.lit(0.0)).alias("score"),
    )
