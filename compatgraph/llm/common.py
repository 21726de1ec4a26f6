"""Shared helpers: materialising in the shared folder, bounded Arrow slices, word splitting."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text bytes handled at once inside a Python worker; longer batches are sliced.
SLICE_BYTES = 4 << 20
#: The contracts' word pattern: everything but ASCII white space.  ``bytes.split()`` splits on the same six bytes.
WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors see: ``spark.checkpoint.dir``.  On one machine (``local[n]``) one of our own where it is unset."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors see")
        at = f"file:///tmp/checkpoints/{spark.sparkContext.applicationId}"
    return at.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet in the shared folder and read it back.

    Unlike a local checkpoint it survives lost executors, and its known size lets Catalyst
    choose a broadcast only below ``spark.sql.autoBroadcastJoinThreshold``.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that the text column of a slice holds about ``limit`` bytes (one row at least)."""
    n = batch.num_rows
    if n == 0:
        return
    step = max(1, int(n * limit / max(limit, batch.column(batch.schema.get_field_index(column)).nbytes)))
    for i in range(0, n, step):
        yield batch.slice(i, step)


#: What an operator left in this Python worker for its next tasks, by a key of its own.
KEPT: dict[str, object] = {}


def release(keeps: str = "") -> None:
    """Drop what other operators left: workers live on through all operators of an application, and their memory counts with the executor's."""
    gone = [k for k in KEPT if k != keeps]
    for k in gone:
        del KEPT[k]
    if gone:
        pa.default_memory_pool().release_unused()


def map_text(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema, column: str = "text", keeps: str = "") -> DataFrame:
    """``mapInArrow`` of a function on bounded slices; ``keeps`` names what ``fn`` leaves in ``KEPT``."""

    def run(batches):
        release(keeps)
        for batch in batches:
            for part in slices(batch, column):
                out = fn(part)
                if out is not None:
                    yield out

    return df.mapInArrow(run, schema)


def texts(batch: pa.RecordBatch, column: str = "text") -> list[str]:
    """The text column as strings, null as empty."""
    return [t or "" for t in batch.column(batch.schema.get_field_index(column)).to_pylist()]


def col(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


class Recent:
    """A cache in two generations: when the young one is full it becomes the old one, and what is used again moves back.

    A generation is full at ``most`` keys, or where its keys hold ``most_chars`` characters.  Frequent keys stay, and memory is bounded by
    two generations and the keys of one slice, which holds ``SLICE_BYTES`` or one text.
    """

    def __init__(self, most: int, most_chars: int = 16 << 20):
        self.most, self.most_chars, self.chars, self.young, self.old = most, most_chars, 0, {}, {}

    def missing(self, keys: set) -> set:
        """Keys to compute and put into ``young``; afterwards all ``keys`` are there."""
        new = keys.difference(self.young)
        more = sum(map(len, new))
        if len(self.young) + len(new) > self.most or self.chars + more > self.most_chars:
            self.old, self.young, new = self.young, {}, keys
            self.chars, more = 0, sum(map(len, keys))
        self.chars += more
        again = [k for k in new if k in self.old]
        self.young.update(zip(again, map(self.old.__getitem__, again), strict=True))
        return new.difference(again)


#: A key is heavy if it holds over one in ``SHARES`` of all rows: at most ``SHARES`` keys are, whatever the input, so they may be broadcast.
SHARES, SALTS = 1_000, 64


def known_bytes(df: DataFrame) -> int:
    """The size that Catalyst's statistics give; for a scan that of its files, without a pass over them."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def heavy(table: DataFrame, key: str, count: str) -> DataFrame:
    """The heavy keys of a table of one row a key with its number of rows; at most ``SHARES`` of them."""
    total = table.agg(F.sum(count)).first()[0] or 0
    return table.filter(F.col(count) * SHARES > total).select(key)


def join_spread(rows: DataFrame, table: DataFrame, key: str, busy: DataFrame) -> DataFrame:
    """Inner join of rows to a table of one row a key; the rows of the ``busy`` keys go to ``SALTS`` tasks each.

    A table below the session's broadcast threshold (by its files' size) goes to the rows instead.  Both sides are narrow tables
    of ours, so the two names below are free.
    """
    if known_bytes(table) <= int(rows.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()):
        return rows.join(F.broadcast(table), key)
    known = F.broadcast(busy.withColumn("_busy", F.lit(True)))
    dealt = rows.join(known, key, "left").withColumn("_salt", F.when(F.col("_busy"), F.pmod(F.monotonically_increasing_id(), F.lit(SALTS))).otherwise(0).cast("int")).drop("_busy")
    copies = F.when(F.col("_busy"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
    copied = table.join(known, key, "left").withColumn("_salt", F.explode(copies)).drop("_busy")
    return dealt.join(copied, [key, "_salt"]).drop("_salt")


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def narrow(docs: DataFrame, *names: str) -> DataFrame:
    """Just the named columns: extra columns, whatever they are called, never reach an operator."""
    return docs.select(*[F.col(f"`{n}`") for n in names])
