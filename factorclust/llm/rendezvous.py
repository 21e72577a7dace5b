"""Sharding by rendezvous hashing (native): each key scores every shard, the best score takes it.

The score of a key and a shard comes from a hash of the two names and the shard's weight alone, so a new
shard takes rows only into itself and a shard that goes only gives its own rows away. Null keys count as
one key of their own. Equal keys share a shard; repeated rows each get their own slot. An empty table
gives an empty result. Extra columns of the input are kept where asked for, under their own names.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factorclust.functions import portable
from factorclust.llm.shared import gapless

#: Hex digits of the digest that are used, and the scale that makes them a number below 1.
DIGITS, SCALE = 13, float(1 << 52)
#: Parts of a shard that are numbered by themselves.
PARTS = 256


def draw(key: Column, shard: int) -> Column:
    """A number in (0, 1) that depends on the key and the shard's name alone."""
    text = F.concat(F.coalesce(key.cast("string"), F.lit("null")), F.lit(f"/{shard}"))
    return (F.conv(F.substring(F.md5(text), 1, DIGITS), 16, 10).cast("double") + 0.5) / SCALE


def shard_of(key: Column, weights: Sequence[float]) -> Column:
    """The shard whose weighted score -weight / ln(draw) is largest; ties go to the smaller shard."""
    if not weights or min(weights) <= 0:
        raise ValueError("weights must be positive, one for each shard")
    scored = [F.struct((-F.lit(float(w)) / F.ln(draw(key, i))).alias("score"), F.lit(-i).alias("less")) for i, w in enumerate(weights)]
    best = F.greatest(*scored) if len(scored) > 1 else scored[0]
    return (-best["less"]).cast("int")


def assign(df: DataFrame, key: str, weights: Sequence[float], out: str = "shard") -> DataFrame:
    return df.withColumn(out, shard_of(F.col(key), weights))


def place(documents: DataFrame, shards: int = 8, weights: Sequence[float] | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot (gapless in each shard) and grown_shard (one shard more).

    The text is read for its size and checksum only; the slots are numbered on narrow rows, each shard dealt
    into parts, so no shard is one task.
    """
    weights = list(weights or [1.0] * shards)
    text = F.col("text").cast("string")
    rows = documents.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1).alias("size"),
        F.coalesce(F.crc32(text.cast("binary")), F.lit(0)).cast("long").alias("text_crc32"),
        F.lit("key").alias("law"),
        shard_of(F.col("doc_id"), weights).alias("shard"),
        shard_of(F.col("doc_id"), [*weights, weights[-1]]).alias("grown_shard"),
    )
    placed = gapless(rows, ["shard"], ["doc_id"], "slot", PARTS, portable.mix(F.coalesce("doc_id", F.lit(0)), 0, 0))
    return placed.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")
