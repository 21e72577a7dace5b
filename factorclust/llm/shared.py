"""Helpers shared by the training-data operators: lineage cuts, shared files, gapless numbers, components."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_own: dict[str, str] = {}
_made: list[tuple[object, object]] = []
#: Called at the end of a task: tables that are cheap to make again.
FORGET: list[Callable[[], None]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or one of our own where that is unset on one machine (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        app = spark.sparkContext.applicationId
        if app not in _own:
            _own[app] = f"file://{tempfile.mkdtemp(prefix='factorclust-')}"
            _remember(spark, _own[app])
        root = _own[app]
    return root.rstrip("/")


def fresh_path(spark: SparkSession, what: str) -> str:
    """A new path below the shared folder; it is removed when the driver ends."""
    path = f"{shared_dir(spark)}/factorclust/{what}-{uuid.uuid4().hex}"
    _remember(spark, path)
    return path


def _remember(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    _made.append((where, where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())))


@atexit.register
def _clean() -> None:
    for where, system in _made:
        try:
            system.delete(where, True)
        except Exception:  # noqa: BLE001  the JVM may be gone already
            return


def bounded_batches(spark: SparkSession, limit: str = "2m", rows: int = 512) -> None:
    """Arrow batches of at most about this size and few rows of a file read at once, whatever the length of the texts
    (settings of the running session)."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", limit)
    spark.conf.set("spark.sql.parquet.columnarReaderBatchSize", rows)


def tidy(run):
    """A function of Arrow batches that gives freed memory back to the system at the end of a task; workers live on."""

    def tidied(batches):
        import ctypes
        import gc

        import pyarrow as pa

        try:
            libc = ctypes.CDLL("libc.so.6")
            libc.mallopt(-3, 1 << 18)  # M_MMAP_THRESHOLD: larger blocks go back to the system as soon as they are freed
        except (OSError, AttributeError):  # another C library
            libc = None
        yield from run(batches)
        for forget in FORGET:
            forget()
        gc.collect()
        pa.default_memory_pool().release_unused()
        if libc:
            libc.malloc_trim(0)

    return tidied


def free_name(taken: list[str], wish: str) -> str:
    """``wish``, with as many underscores before it as tell it from the columns taken."""
    used = {c.lower() for c in taken}
    while wish.lower() in used:
        wish = f"_{wish}"
    return wish


def cut(df: DataFrame, what: str = "cut") -> DataFrame:
    """Writes ``df`` as a table in the shared folder and reads it again: later stages restart from it."""
    path = fresh_path(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def crc_mod(key: str, n: int) -> Column:
    """crc32 of the key as text, modulo ``n``."""
    return F.pmod(F.crc32(F.col(key).cast("string")), F.lit(n))


def gapless(df: DataFrame, group: list[str], order: list[str], out: str, parts: int = 256, spread: Column | None = None) -> DataFrame:
    """Numbers the rows of each group from 0 without gaps, in no stated order.

    A group may hold any share of all rows, so it is dealt into ``parts`` by a hash of ``order`` (or by
    ``spread``); each part is numbered by itself and starts where the parts before it end. ``df`` is read twice.
    """
    dealt = df.withColumn("__part", F.pmod(F.xxhash64(*order) if spread is None else spread, F.lit(parts)).cast("int"))
    sizes = dealt.groupBy(*group, "__part").agg(F.count(F.lit(1)).alias("__n"))
    before = F.sum("__n").over(Window.partitionBy(*group).orderBy("__part")) - F.col("__n")
    starts = sizes.select(*[F.col(g).alias(f"__g{i}") for i, g in enumerate(group)], F.col("__part").alias("__p"), before.alias("__before"))
    inside = F.row_number().over(Window.partitionBy(*group, "__part").orderBy(*order))
    same = F.col("__part") == F.col("__p")
    for i, g in enumerate(group):
        same = same & F.col(g).eqNullSafe(F.col(f"__g{i}"))
    numbered = dealt.withColumn("__inside", inside).join(starts, same)
    return numbered.withColumn(out, (F.col("__before") + F.col("__inside") - 1).cast("long")).drop("__part", "__p", "__before", "__inside", *[f"__g{i}" for i in range(len(group))])


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """Connected components of ``edges`` (a long, b long) as (node, comp); comp is the smallest node.

    Least labels spread over the edges, then each label is replaced by its own label, so long chains
    halve with each round. Only aggregates and joins; no group is gathered.
    """
    pairs = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct()
    both = cut(pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))), "edges")
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("comp")), "labels")
    for _ in range(rounds):
        near = both.join(labels, both.b == labels.node).groupBy("a").agg(F.min("comp").alias("m"))
        spread = labels.join(near, labels.node == near.a).select("node", F.col("comp").alias("old"), F.least("comp", "m").alias("comp"))
        up = labels.select(F.col("node").alias("n2"), F.col("comp").alias("c2"))
        moved = cut(spread.join(up, spread.comp == up.n2).select("node", "old", F.least("comp", "c2").alias("comp")), "labels")
        labels = moved.select("node", "comp")
        if moved.where("old <> comp").isEmpty():
            return labels
    raise RuntimeError(f"components: not settled after {rounds} rounds")
