"""MinHash near-duplicate detection by a multi-index Hamming join.

A document's set holds its distinct 5-word shingles (64-bit hashes).  Equal sets are one node.  A signature has ``HASHES``
b-bit minhash symbols (b = 16); at similarity s a symbol differs with probability 1 - s.  Signatures that differ in
at most ``DISTANCE`` symbols are all found: by the pigeonhole principle one of ``CHUNKS`` chunks differs in at most
``DISTANCE // CHUNKS`` = 1 symbol, and each chunk is indexed with each one of its symbols left out.  At similarity 0.75 a
pair is beyond that distance with probability 2e-5; every candidate is confirmed on the full sets.

1. Each index key links its nodes to its smallest node (a star), which is confirmed on the full sets.
2. Components of the confirmed links.  Keys whose nodes are all in one component are done.
3. In the other keys, nodes of different components are compared in blocks of at most ``BLOCK`` nodes, and pairs within the
   distance confirmed; a pair comes from the first key that it shares.

Before a pair is confirmed, two bounds that lose no link thin the pairs out: the sets' sizes, and parity sketches.  A
sketch has one bit for each of ``PARITY`` cells, set if an odd number of shingles falls into it; sets differ in at least as
many shingles as their sketches differ in bits, and linked sets differ in at most a seventh of their sizes' sum (at 75 %).
So no key's pairs are all emitted, and no link between components is lost.

Nodes get numbers of their own when they are written down; doc_ids are only carried and compared, so they may have any type with
an order.  Null and empty texts have the empty set, are linked with nothing and skip every join.  Null doc_ids sort below all others
(their component_id is null).  Rows that share a doc_id are each judged by their own text: those of a component's smallest doc_id are
all kept, so callers that want one row need doc_ids that differ.  An empty table gives an empty result; very long texts
are read whole; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import col, heavy, join_spread, map_text, materialise, texts
from .components import connected
from .substring_dedup import gram_hashes, mixed, word_hashes

SHINGLE, HASHES, CHUNKS, DISTANCE, BLOCK, PARITY = 5, 64, 16, 31, 4_000, 2_048
#: Nodes whose ids are broadcast at most (about 100 bytes each); beyond it the texts are shuffled to them.
BROADCAST_IDS = 500_000
_SEEDS = np.random.default_rng(20_240_229).integers(1, 2**63, (2, HASHES), dtype=np.uint64) | np.uint64(1)


def shingle_sets(batch: list[str]) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    docs = [t.encode().lower().split() for t in batch]
    h = word_hashes([w for d in docs for w in d])
    grams, out, at = gram_hashes(h, SHINGLE), [], 0
    for d in docs:
        n = len(d)
        if n >= SHINGLE:
            out.append(np.unique(grams[at : at + n - SHINGLE + 1]))
        else:
            out.append(mixed(gram_hashes(h[at : at + n], n) + np.uint64(n)) if n else np.zeros(0, np.uint64))
        at += n
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """A row of ``HASHES`` 16-bit symbols for each set that isn't empty."""
    size = np.array([len(s) for s in sets])
    flat, first = np.concatenate(sets), np.cumsum(size) - size
    out = np.empty((len(sets), HASHES), np.uint16)
    for j in range(HASHES):
        least = np.minimum.reduceat((flat ^ _SEEDS[0, j]) * _SEEDS[1, j], first)
        out[:, j] = (least >> np.uint64(20)).astype(np.uint16)
    return out


def index_keys(sig: np.ndarray) -> np.ndarray:
    """For each signature its CHUNKS * 4 keys: 3 symbols of a chunk of 4, and which."""
    width = HASHES // CHUNKS
    chunks = sig.reshape(len(sig), CHUNKS, width).astype(np.int64)
    keys = []
    for c in range(CHUNKS):
        for skip in range(width):
            key = np.full(len(sig), c * width + skip, np.int64)
            for j in range(width):
                if j != skip:
                    key = (key << 16) | chunks[:, c, j]
            keys.append(key)
    return np.stack(keys, 1)


def parity_sketch(s: np.ndarray) -> bytes:
    return np.packbits((np.bincount((s >> np.uint64(7)).astype(np.int64) % PARITY, minlength=PARITY) & 1).astype(np.uint8)).tobytes()


def _array(batch, column: str, kind, width: int) -> np.ndarray:
    return np.frombuffer(b"".join(batch.column(column).to_pylist()), kind).reshape(-1, width)


def may_link(oa: np.ndarray, ob: np.ndarray, na: np.ndarray, nb: np.ndarray, percent: int) -> np.ndarray:
    """False only where sizes and sketches rule out ``percent`` similarity: 100 * both >= percent * either."""
    apart = np.bitwise_count(oa ^ ob).sum(-1).astype(np.int64)
    return (100 * np.minimum(na, nb) >= percent * np.maximum(na, nb)) & ((100 + percent) * apart <= (100 - percent) * (na + nb))


def _signed(batch: pa.RecordBatch) -> pa.RecordBatch:
    sets = shingle_sets(texts(batch))
    full = [i for i, s in enumerate(sets) if len(s)]
    sigs: list = [None] * len(sets)
    digests: list = [None] * len(sets)
    odds: list = [None] * len(sets)
    if full:
        for i, s in zip(full, signatures([sets[i] for i in full]), strict=True):
            sigs[i], digests[i], odds[i] = s.tobytes(), hashlib.blake2b(sets[i].tobytes(), digest_size=16).digest(), parity_sketch(sets[i])
    return pa.RecordBatch.from_arrays([col(batch, "did"), pa.array([len(s) for s in sets], pa.int64()), pa.array(digests, pa.binary()), pa.array(sigs, pa.binary()), pa.array(odds, pa.binary())], names=["did", "n", "digest", "sig", "odd"])


def _keyed(batches):
    for batch in batches:
        for i in range(0, batch.num_rows, 2_000):
            part = batch.slice(i, 2_000)
            keys = index_keys(np.frombuffer(b"".join(part.column(1).to_pylist()), np.uint16).reshape(-1, HASHES))
            yield pa.RecordBatch.from_arrays([pa.array(keys.ravel()), part.column(0).take(pa.array(np.repeat(np.arange(len(keys)), keys.shape[1])))], names=["key", "id"])


def _close(percent: int):
    """Of pairs (a, na, sa, oa, b, nb, sb, ob) those within the signature distance that may link."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                keep = (_array(batch, "sa", np.uint16, HASHES) != _array(batch, "sb", np.uint16, HASHES)).sum(1) <= DISTANCE
                keep &= may_link(_array(batch, "oa", np.uint64, PARITY // 64), _array(batch, "ob", np.uint64, PARITY // 64), col(batch, "na").to_numpy(), col(batch, "nb").to_numpy(), percent)
                yield pa.RecordBatch.from_arrays([col(batch, "a"), col(batch, "b")], names=["a", "b"]).filter(pa.array(keep))

    return run


def _linked(percent: int):
    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(col(batch, "xa"), col(batch, "xb"), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([col(batch, "a"), col(batch, "b")], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def first_shared(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Number of the first index key that signatures share (they share one)."""
    same = (x == y).reshape(len(y), CHUNKS, HASHES // CHUNKS)
    chunk = (same.sum(2) >= HASHES // CHUNKS - 1).argmax(1)
    own = same[np.arange(len(y)), chunk]
    return chunk * (HASHES // CHUNKS) + np.where(own.all(1), 0, (~own).argmax(1))


def _across(percent: int):
    """Pairs of one key (and pair of blocks) in different components that may link, where the key is the first they share."""

    def run(table: pa.Table) -> pa.Table:
        ids, comp = table.column("id").to_numpy(), table.column("comp").to_numpy()
        own, n = table.column("block").to_numpy(), table.column("n").to_numpy()
        x, y, key = table.column("x")[0].as_py(), table.column("y")[0].as_py(), table.column("key")[0].as_py() >> 48
        sig, odd = _array(table, "sig", np.uint16, HASHES), _array(table, "odd", np.uint64, PARITY // 64)
        a, b = [], []
        left, right = np.flatnonzero(own == x), np.flatnonzero(own == y)
        for i in left.tolist():
            cand = right[(comp[right] != comp[i]) & ((ids[right] > ids[i]) if x == y else True)]
            cand = cand[may_link(odd[cand], odd[i], n[cand], n[i], percent)] if len(cand) else cand
            cand = cand[(sig[cand] != sig[i]).sum(1) <= DISTANCE] if len(cand) else cand
            cand = cand[first_shared(sig[i], sig[cand]) == key] if len(cand) else cand
            a += [ids[i]] * len(cand)
            b += ids[cand].tolist()
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


def near_duplicates(docs: DataFrame, *, percent: int = 75, block: int = BLOCK) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every document; ``percent`` is the least similarity (75 at least)."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    # a struct: null doc_ids compare as the smallest and take part in minima
    rows = docs.select(F.struct(F.col("`doc_id`").alias("id")).alias("did"), F.col("`text`").alias("text"))
    signed = materialise(map_text(rows, _signed, f"did struct<id:{kind}>, n long, digest binary, sig binary, odd binary"), "near-signatures")
    nodes = signed.filter("n > 0").groupBy("digest").agg(F.min("did").alias("first"), F.count(F.lit(1)).alias("copies"), F.first("n").alias("n"), F.first("sig").alias("sig"), F.first("odd").alias("odd"))
    nodes = materialise(nodes.withColumn("id", F.monotonically_increasing_id()), "near-nodes")
    keys = nodes.select("id", "sig").mapInArrow(_keyed, "key long, id long")
    shared = keys.groupBy("key").agg(F.min("id").alias("lead"), F.max("id").alias("top"), F.count(F.lit(1)).alias("size")).filter("lead < top").drop("top")
    index = materialise(keys.join(shared, "key"), "near-index")

    # the texts of the nodes that share a key
    some = nodes.join(index.select("id").distinct(), "id", "left_semi").select("first", "id", F.col("digest").alias("own"))
    some = materialise(some, "near-candidates")
    near = F.broadcast(some) if some.count() <= BROADCAST_IDS else some
    own = rows.join(near, rows.did == near["first"]).select("id", "own", "text")

    def kept_sets(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [x.tobytes() for x in shingle_sets(texts(batch))]
        # of rows that share a doc_id only those of the node's text count
        mine = [hashlib.blake2b(x, digest_size=16).digest() == d for x, d in zip(sets, col(batch, "own").to_pylist(), strict=True)]
        return pa.RecordBatch.from_arrays([col(batch, "id"), pa.array(sets, pa.binary())], names=["id", "set"]).filter(pa.array(mine, pa.bool_()))

    sets = materialise(map_text(own, kept_sets, "id long, set binary"), "near-sets")
    if sets.count() > some.count():  # wholly repeated rows: one of each
        sets = materialise(sets.dropDuplicates(["id"]), "near-sets")
    facts = nodes.select("id", "n", "sig", "odd")

    def close(pairs: DataFrame) -> DataFrame:
        for side in ("a", "b"):
            pairs = pairs.join(facts.select(F.col("id").alias(side), F.col("n").alias(f"n{side}"), F.col("sig").alias(f"s{side}"), F.col("odd").alias(f"o{side}")), side)
        return pairs.mapInArrow(_close(percent), "a long, b long").distinct()

    def confirm(pairs: DataFrame) -> DataFrame:
        a, b = sets.select(F.col("id").alias("a"), F.col("set").alias("xa")), sets.select(F.col("id").alias("b"), F.col("set").alias("xb"))
        return pairs.join(a, "a").join(b, "b").select("a", "xa", "b", "xb").mapInArrow(_linked(percent), "a long, b long").distinct()

    stars = close(index.filter("id <> lead").select(F.col("lead").alias("a"), F.col("id").alias("b")).distinct())
    links = materialise(confirm(stars), "near-links")
    comps = connected(links)
    named = index.join(comps.withColumnRenamed("node", "id"), "id", "left").withColumn("comp", F.coalesce("comp", "id"))
    open_keys = named.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).filter("low < high").select("key")
    # a key of more nodes than a block is compared block by block
    blocks = F.ceil(F.col("size") / block).cast("int")
    dealt = named.join(open_keys, "key").join(facts, "id").withColumn("block", F.pmod(F.xxhash64("id"), blocks).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1))).withColumn("x", F.least("block", "other")).withColumn("y", F.greatest("block", "other"))
    rest = dealt.select("key", "x", "y", "id", "comp", "block", "n", "sig", "odd").groupBy("key", "x", "y").applyInArrow(_across(percent), "a long, b long").distinct()
    more = materialise(confirm(rest), "near-links")
    comps = connected(links.unionByName(more))

    tied = nodes.select("id", "digest", "first", "copies").join(comps.withColumnRenamed("node", "id"), "id", "left")
    lowest = tied.filter("comp is not null").groupBy("comp").agg(F.min("first").alias("low"))
    places = materialise(tied.join(lowest, "comp", "left").select("digest", "copies", F.coalesce("low", "first").alias("low")), "near-places")
    found = join_spread(signed.filter("n > 0").select("did", "n", "digest"), places.drop("copies"), "digest", heavy(places, "digest", "copies"))
    out = found.select("did", "n", "low").unionByName(signed.filter("n = 0").select("did", "n", F.col("did").alias("low")))
    return out.select(F.col("did.id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("low.id").alias("component_id"), F.col("did.id").eqNullSafe(F.col("low.id")).alias("kept"))
