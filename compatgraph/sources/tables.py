"""Scans, readers, edge normalisation and graph builders on ordinary tables.

``edges`` are (src LONG, dst LONG, w DOUBLE), both directions stored; ``labels`` are (node LONG, cls INT).
Two key spaces share one id space by packing: ``2 * id`` and ``2 * id + 1``.
"""

from __future__ import annotations

from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("w", T.DoubleType())])
TURN_SPAN = 4096
#: Query vectors that a task holds while others are streamed past them.
QUERIES = 20_000


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """Parquet scan of the named columns only."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edges(spark: SparkSession, path: str, kind: str = "csv", **options) -> DataFrame:
    """Edge list in CSV, TSV, JSON or ORC with the fixed schema; malformed rows become null and are dropped."""
    if kind == "orc":
        return spark.read.schema(EDGES).orc(path)
    if kind == "json":
        return spark.read.schema(EDGES).json(path, mode="PERMISSIVE").na.drop()
    return spark.read.schema(EDGES).csv(path, header=True, sep="\t" if kind == "tsv" else ",", mode="PERMISSIVE", **options).na.drop()


def check_schema(df: DataFrame, schema: T.StructType = EDGES) -> DataFrame:
    """``df`` if it has the schema's columns with their types, else an error that names the first difference."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if have.get(f.name) != f.dataType:
            raise TypeError(f"column {f.name} should be {f.dataType.simpleString()}, is {have[f.name].simpleString() if f.name in have else 'missing'}")
    return df


def normalise_edges(pairs: DataFrame) -> DataFrame:
    """(a, b, w) -> edges: no self-loops, no bad weights, parallel pairs summed, both directions."""
    good = pairs.filter("a <> b and w > 0 and not isnan(w)").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.col("w").cast("double").alias("w"))
    once = good.groupBy("a", "b").agg(F.sum("w").alias("w"))
    # one expansion after the only shuffle, in place of a union of two scans
    return once.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), "w"), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), "w"))).alias("e")).select("e.src", "e.dst", "e.w")


def trade(spark, d) -> DataFrame:
    """Customer-supplier pairs by lines of orders."""
    o, l = table(spark, d, "orders", "o_orderkey", "o_custkey"), table(spark, d, "lineitem", "l_orderkey", "l_suppkey")
    return normalise_edges(l.join(o, l.l_orderkey == o.o_orderkey).select((2 * F.col("o_custkey")).alias("a"), (2 * F.col("l_suppkey") + 1).alias("b"), F.lit(1.0).alias("w")))


def trade_labels(spark, d) -> DataFrame:
    n = table(spark, d, "nation", "n_nationkey", "n_regionkey")
    c = table(spark, d, "customer", "c_custkey", "c_nationkey").select((2 * F.col("c_custkey")).alias("node"), F.col("c_nationkey").alias("n_nationkey"))
    s = table(spark, d, "supplier", "s_suppkey", "s_nationkey").select((2 * F.col("s_suppkey") + 1).alias("node"), F.col("s_nationkey").alias("n_nationkey"))
    return c.unionByName(s).join(n, "n_nationkey").select("node", F.col("n_regionkey").cast("int").alias("cls"))


def copart(spark, d) -> DataFrame:
    """Parts that share an order; weight: orders shared.  An order has few lines, so the self-join stays near the input."""
    l = table(spark, d, "lineitem", "l_orderkey", "l_partkey").distinct()
    r = l.withColumnRenamed("l_partkey", "b")
    return normalise_edges(l.join(r, "l_orderkey").filter("l_partkey < b").select(F.col("l_partkey").alias("a"), "b", F.lit(1.0).alias("w")))


def turn_node(conv, turn):
    """Node id of a turn: packed and not negative within ``TURN_SPAN`` turns of a conversation, else negative by a 63-bit hash of both keys."""
    packed = turn.between(0, TURN_SPAN - 1) & conv.between(0, (1 << 51) - 1)
    hashed = F.xxhash64(conv.cast("long"), turn.cast("long")).bitwiseOR(F.lit(-(1 << 63)))
    return F.when(packed, conv * TURN_SPAN + turn).when(conv.isNotNull() & turn.isNotNull(), hashed)


def turns(spark, d) -> DataFrame:
    """Consecutive turns of a conversation."""
    c = table(spark, d, "conversations", "conv_id", "turn")
    nxt = F.lead("turn").over(W.partitionBy("conv_id").orderBy("turn"))
    pairs = c.select("conv_id", "turn", nxt.alias("next"))
    return normalise_edges(pairs.select(turn_node(F.col("conv_id"), F.col("turn")).alias("a"), turn_node(F.col("conv_id"), F.col("next")).alias("b"), F.lit(1.0).alias("w")).filter("b is not null"))


def turn_labels(spark, d) -> DataFrame:
    """assistant 0, system 1, user 2."""
    c = table(spark, d, "conversations", "conv_id", "turn", "role")
    return c.select(turn_node(F.col("conv_id"), F.col("turn")).alias("node"), F.expr("case role when 'assistant' then 0 when 'system' then 1 else 2 end").alias("cls"))


def steps(spark, d) -> DataFrame:
    """Consecutive events of a user."""
    e = table(spark, d, "events", "event_id", "ts", "user_id")
    nxt = F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    return normalise_edges(e.select(F.col("event_id").alias("a"), nxt.alias("b"), F.lit(1.0).alias("w")).filter("b is not null"))


def tree(spark, d) -> DataFrame:
    """Region - nation - customer and supplier forest, packed by 4."""
    n, c, s = table(spark, d, "nation", "n_nationkey", "n_regionkey"), table(spark, d, "customer", "c_custkey", "c_nationkey"), table(spark, d, "supplier", "s_suppkey", "s_nationkey")
    up = lambda a, b: [(4 * a).cast("long").alias("a"), b.cast("long").alias("b"), F.lit(1.0).alias("w")]
    pairs = n.select(*up(F.col("n_regionkey"), 4 * F.col("n_nationkey") + 1))
    child = lambda key, nation, k: [(4 * F.col(nation) + 1).cast("long").alias("a"), (4 * F.col(key) + k).cast("long").alias("b"), F.lit(1.0).alias("w")]
    return normalise_edges(pairs.unionByName(c.select(*child("c_custkey", "c_nationkey", 2))).unionByName(s.select(*child("s_suppkey", "s_nationkey", 3))))


def tree_labels(spark, d) -> DataFrame:
    """The region of every node of the forest."""
    n = table(spark, d, "nation", "n_nationkey", "n_regionkey")
    of = lambda df, key, nation, k: df.join(n, df[nation] == n.n_nationkey).select((4 * F.col(key) + k).cast("long").alias("node"), F.col("n_regionkey").cast("int").alias("cls"))
    own = n.select((4 * F.col("n_regionkey")).cast("long").alias("node"), F.col("n_regionkey").cast("int").alias("cls")).distinct()
    own = own.unionByName(n.select((4 * F.col("n_nationkey") + 1).cast("long").alias("node"), F.col("n_regionkey").cast("int").alias("cls")))
    return own.unionByName(of(table(spark, d, "customer", "c_custkey", "c_nationkey"), "c_custkey", "c_nationkey", 2)).unionByName(of(table(spark, d, "supplier", "s_suppkey", "s_nationkey"), "s_suppkey", "s_nationkey", 3))


def same_text(spark, d) -> DataFrame:
    """Documents of equal text, tied to the smallest doc_id of the text: a star, not all pairs of a group."""
    docs = table(spark, d, "documents", "doc_id", "text").select("doc_id", F.sha2("text", 256).alias("h"))
    first = docs.groupBy("h").agg(F.min("doc_id").alias("a"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    return normalise_edges(docs.join(first, "h").select("a", F.col("doc_id").alias("b"), F.lit(1.0).alias("w")))


def pages(spark, d) -> DataFrame:
    """Page-link bipartite graph; a link's id comes from its hash."""
    p = table(spark, d, "pages", "page_id", "html")
    href = F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), 1)))
    key = F.conv(F.substring(F.md5("href"), 1, 12), 16, 10).cast("long")
    return normalise_edges(p.select("page_id", href.alias("href")).select((2 * F.col("page_id")).alias("a"), (2 * key + 1).alias("b"), F.lit(1.0).alias("w")))


def link_ids(spark, d) -> DataFrame:
    """id, href of the distinct links of pages."""
    p = table(spark, d, "pages", "html")
    href = p.select(F.explode(F.regexp_extract_all("html", F.lit('<a href="([^"]*)"'), 1)).alias("href")).distinct()
    return href.select(F.conv(F.substring(F.md5("href"), 1, 12), 16, 10).cast("long").alias("id"), "href")


def collisions(ids: DataFrame) -> DataFrame:
    """collisions: strings beyond the first of an id.  48-bit ids are for up to some million strings; this tells."""
    return ids.groupBy("id").agg((F.count(F.lit(1)) - 1).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("collisions"))


def page_labels(spark, d) -> DataFrame:
    """The language that a page declares, by alphabet; links have none."""
    p = table(spark, d, "pages", "page_id", "html").select((2 * F.col("page_id")).alias("node"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("lang"))
    p = p.filter("lang <> ''")
    names = p.select("lang").distinct()
    return p.join(F.broadcast(names.withColumn("cls", (F.row_number().over(W.orderBy("lang")) - 1).cast("int"))), "lang").select("node", "cls")


def shared_lines(spark, d, least: int = 40) -> DataFrame:
    """Documents that share a line of ``least`` characters or more, tied to the line's smallest doc_id: a star a line, not all pairs."""
    docs = table(spark, d, "documents", "doc_id", "text")
    lines = docs.select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).filter(F.length("line") >= least).select("doc_id", F.sha2("line", 256).alias("h"))
    first = lines.groupBy("h").agg(F.min("doc_id").alias("a"), F.count(F.lit(1)).alias("n")).filter("n > 1")
    return normalise_edges(lines.join(first, "h").select("a", F.col("doc_id").alias("b"), F.lit(1.0).alias("w")))


def doc_labels(spark, d, of: str) -> DataFrame:
    """quality or toxic, of the documents that have it."""
    return table(spark, d, "labels", "doc_id", of).filter(F.col(of).isNotNull()).select(F.col("doc_id").alias("node"), F.col(of).cast("int").alias("cls"))


def step_labels(spark, d) -> DataFrame:
    """Event types by alphabet."""
    e = table(spark, d, "events", "event_id", "event_type")
    names = e.select("event_type").distinct()
    return e.join(F.broadcast(names.withColumn("cls", (F.row_number().over(W.orderBy("event_type")) - 1).cast("int"))), "event_type").select(F.col("event_id").alias("node"), "cls")


def cosine(a: str, b: str):
    """Cosine of two arrays in double precision, in generated code."""
    product = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, p: s + p)
    return product(a, b) / F.sqrt(product(a, a) * product(b, b))


def _rounded(cos: np.ndarray) -> np.ndarray:
    """Six decimals, halves away from zero by the shortest decimal form, as the JVM rounds."""
    scaled = np.abs(cos) * 1e6
    out = np.floor(scaled + 0.5)
    for i in np.flatnonzero(np.abs(scaled - np.floor(scaled) - 0.5) < 1e-6):
        out[i] = float(Decimal(repr(float(abs(cos[i])))).scaleb(6).quantize(Decimal(1), ROUND_HALF_UP))
    return np.copysign(out / 1e6, cos)


class _Best:
    """The ``k`` nearest of each query vector among those met so far."""

    def __init__(self, k: int):
        self.k, self.ids, self.x = k, np.empty(0, np.int64), []
        self.row, self.cos, self.b = np.empty(0, np.int64), np.empty(0), np.empty(0, np.int64)

    def queries(self, ids: np.ndarray, x: np.ndarray) -> None:
        self.ids = np.concatenate([self.ids, ids])
        self.x.append(x)

    def meet_own(self) -> _Best:
        """The queries meet each other."""
        if self.x:
            self.meet(self.ids, np.concatenate(self.x))
        return self

    @staticmethod
    def scaled(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Columns, sums of squares in order of the elements, unit rows."""
        columns, squares = np.ascontiguousarray(x.T), np.zeros(len(x))
        for c in columns:
            squares += c * c
        if not (squares > 0).all():
            raise ValueError("a vector without direction has no cosine")
        return columns, squares, x / np.sqrt(squares)[:, None]

    def meet(self, ids: np.ndarray, x: np.ndarray, block: int = 1024) -> None:
        if isinstance(self.x, list):
            self.x = self.scaled(np.concatenate(self.x)) if self.x else None
            self.least = np.full(len(self.ids), -np.inf)
        if self.x is None:
            return
        for i in range(0, len(ids), block):
            other = self.scaled(x[i : i + block])
            for q in range(0, len(self.ids), block):
                self._block(q, q + block, ids[i : i + block], other)

    def _block(self, lo: int, hi: int, ids: np.ndarray, other: tuple) -> None:
        sim = self.x[2][lo:hi] @ other[2].T
        sim[self.ids[lo:hi, None] == ids] = -np.inf
        least = self.least[lo:hi]
        if np.isinf(least).any() and len(ids) > self.k:
            least = np.maximum(least, np.partition(sim, -self.k, axis=1)[:, -self.k])
        # rounding moves a cosine by half a millionth at most
        r, c = np.nonzero((sim >= least[:, None] - 2e-6) & (sim > -np.inf))
        if not len(r):
            return
        r, dot = r + lo, np.zeros(len(r))
        for u, v in zip(self.x[0], other[0], strict=True):
            dot += u[r] * v[c]
        own = (self.row >= lo) & (self.row < hi)
        row = np.concatenate([self.row[own], r])
        cos = np.concatenate([self.cos[own], _rounded(dot / np.sqrt(self.x[1][r] * other[1][c]))])
        b = np.concatenate([self.b[own], ids[c]])
        order = np.lexsort((b, -cos, row))
        row, cos, b = row[order], cos[order], b[order]
        pos = np.arange(len(row)) - np.searchsorted(row, row)
        last, few = row[pos == self.k - 1], pos < self.k
        self.least[last] = cos[pos == self.k - 1]
        self.row, self.cos, self.b = (np.concatenate([old[~own], found[few]]) for old, found in ((self.row, row), (self.cos, cos), (self.b, b)))

    def batch(self) -> pa.RecordBatch:
        return pa.RecordBatch.from_pydict({"a": self.ids[self.row], "b": self.b, "cos": self.cos})


def _best_rows(dealt: DataFrame, k: int, tasks: int) -> DataFrame:
    """a, b, cos: in each group ``g`` of ``dealt(g, kind, id, embedding)`` the ``k`` nearest of its rows of kind 0, among all its rows.

    A task holds the rows of kind 0 of one group; those of kind 1 are streamed past them.
    """

    def run(batches):
        at, best, met = None, None, False
        for batch in batches:
            if not batch.num_rows:
                continue
            g, kind, ids = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            flat = batch.column(3).flatten()
            if flat.null_count or len(flat) % max(1, len(g)) or len(set(batch.column(3).value_lengths().to_pylist())) > 1:
                raise ValueError("vectors of several lengths, or with null elements")
            x = flat.to_numpy(zero_copy_only=False).astype(float).reshape(len(g), -1)
            cuts = [0, *(np.flatnonzero((np.diff(g) != 0) | (np.diff(kind) != 0)) + 1).tolist(), len(g)]
            for lo, hi in zip(cuts, cuts[1:]):
                if lo == hi:
                    continue
                if g[lo] != at:
                    if best is not None:
                        yield best.batch() if met else best.meet_own().batch()
                    at, best, met = g[lo], _Best(k), False
                if not kind[lo]:
                    best.queries(ids[lo:hi], x[lo:hi])
                    continue
                if not met:
                    best.meet_own()
                met = True
                best.meet(ids[lo:hi], x[lo:hi])
        if best is not None:
            yield best.batch() if met else best.meet_own().batch()

    return dealt.select("g", "kind", "id", "embedding").repartition(tasks, "g").sortWithinPartitions("g", "kind").mapInArrow(run, "a long, b long, cos double")


def _all_pairs(v: DataFrame, k: int, n: int) -> DataFrame:
    """a, b, cos with the ``k`` nearest of each row and no others: groups of query vectors, each streamed past by all vectors."""
    groups = max(12, -(-n // QUERIES))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(groups)).cast("int")
    g = F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))
    dealt = v.select(g.alias("g"), own.alias("own"), F.col("vec_id").cast("long").alias("id"), "embedding")
    return _best_rows(dealt.withColumn("kind", (F.col("g") != F.col("own")).cast("int")), k, 2 * groups)


def _hashed_pairs(v: DataFrame, k: int, planes: np.ndarray) -> DataFrame:
    """a, b, cos with the ``k`` nearest of each row in each of its buckets and no others.

    A bucket of over ``QUERIES`` vectors is cut into groups of about that many queries; all its vectors are streamed past each.
    """
    tables, bits, _ = planes.shape
    kind = v.schema["embedding"].dataType.simpleString()

    def signed(batches):
        for batch in batches:
            x = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, -1)
            keys = np.empty((len(x), tables), np.int64)
            for t, plane in enumerate(planes):
                keys[:, t] = t << bits
                for i, p in enumerate(plane):
                    total = np.zeros(len(x))
                    for column, y in zip(x.T, p, strict=True):  # in order of the elements
                        total += column * y
                    keys[:, t] |= (total > 0).astype(np.int64) << i
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.FixedSizeListArray.from_arrays(pa.array(keys.ravel()), tables).cast(pa.list_(pa.int64()))], names=["id", "embedding", "keys"])

    keyed = v.select(F.col("vec_id").cast("long").alias("id"), "embedding").mapInArrow(signed, f"id long, embedding {kind}, keys array<long>").select("id", "embedding", F.explode("keys").alias("key"))
    parts = keyed.groupBy("key").agg(F.ceil(F.count(F.lit(1)) / QUERIES).cast("long").alias("parts"))
    dealt = keyed.join(F.broadcast(parts) if tables << bits <= 100_000 else parts, "key").withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    dealt = dealt.withColumn("kind", (F.pmod(F.xxhash64("id"), F.col("parts")) != F.col("part")).cast("int"))
    return _best_rows(dealt.withColumn("g", F.col("key") * F.lit(1 << 24) + F.col("part")), k, min(2 * tables << bits, 2_000))


def nearest(vectors: DataFrame, k: int = 5, *, bits: int = 0, tables: int = 1, seed: int = 1, most: int | None = None) -> DataFrame:
    """a, b, cos, pos: the ``k`` nearest of each vector of (vec_id, embedding) by cosine, ties by id.

    With ``bits`` only vectors that share the signs of that many random projections in one of ``tables`` hash tables meet, in the blocks
    of their buckets: approximate.  Without, all meet, in blocks: exact at every size, with work that grows as its square; ``most`` refuses
    larger tables for callers that want that.  Either way a vector's pairs are cut to its ``k`` nearest where they are found.  Vectors need
    one length and a direction.
    """
    v = vectors.filter("vec_id is not null and embedding is not null and size(embedding) > 0").select("vec_id", "embedding")
    best = W.partitionBy("a").orderBy(F.desc("cos"), "b")
    if not bits:
        n = v.count()
        if most is not None and n > most:
            raise ValueError(f"{n} vectors: the exact way is for at most {most}, give bits")
        found = _all_pairs(v, k, n)
    else:
        first = v.first()
        planes = np.random.default_rng(seed).standard_normal((tables, bits, len(first.embedding) if first else 1)).round(6)
        found = _hashed_pairs(v, k, planes)
        if tables > 1:  # one exchange, by a, serves this and the ranks
            found = found.repartition("a").dropDuplicates(["a", "b"])
    return found.withColumn("pos", F.row_number().over(best)).filter(F.col("pos") <= k)


def knn(spark, d, k: int = 5, **options) -> DataFrame:
    """Neighbour graph of the embeddings: an edge where either is among the k nearest of the other."""
    near = nearest(table(spark, d, "embeddings", "vec_id", "embedding"), k, **options)
    return normalise_edges(near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.lit(1.0).alias("w")).distinct())


def write_bucketed(edges: DataFrame, name: str, buckets: int = 64) -> None:
    """Edges bucketed by their sending node: propagation steps then never exchange them."""
    edges.write.bucketBy(buckets, "dst").sortBy("dst").mode("overwrite").saveAsTable(name)


def write_run(df: DataFrame, path: str, run: str) -> None:
    """Beliefs, predictions, a K or records of one run as a partition ``run=...`` of a Parquet folder; a second write replaces that run only."""
    df.withColumn("run", F.lit(run)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run").parquet(path)
