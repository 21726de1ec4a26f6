"""Exact substring deduplication by super-k-mer partitioning.

A window is ``k`` consecutive words of one document.  Its minimiser is the least hash among its ``m``-word
grams, the leftmost on ties.  Consecutive windows with the minimiser at one place form a super-k-mer.  Equal windows
have equal minimisers at equal offsets, so they lie in different super-k-mers of one bucket (the
minimiser's hash), and a super-k-mer whose bucket holds nothing else has only unique windows.

1. Buckets are counted (narrow rows, combined in the map tasks).  Those with one super-k-mer are done.
2. The others' super-k-mers travel as one packed string each to their bucket, where sorting the windows counts them
   exactly.  A bucket of more than ``hot`` strings is not gathered: its windows are counted by 128-bit digest, combined in the
   map tasks, and looked up by a join that spreads the windows of a frequent digest, so no task gets a whole hot bucket or window.
3. The repeated windows come back as word ranges, and the covered words are removed.

Null and empty texts have no words.  Documents of fewer than ``k`` words have no window.  Repeated rows repeat each
other's windows and lose them.  Rows are told apart by doc_id (nulls alike) and text hash.  An empty table gives an empty
result; very long texts are cut into super-k-mers whole; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SALTS, col, heavy, map_text, materialise, texts

K, M, HOT = 35, 8, 20_000
_MUL = np.uint64(0x9E3779B97F4A7C15)


def word_hashes(words: list[bytes]) -> np.ndarray:
    import xxhash

    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def gram_hashes(h: np.ndarray, m: int) -> np.ndarray:
    """Hash of the ``m`` words from each place."""
    n = len(h) - m + 1
    out = np.zeros(max(0, n), np.uint64)
    for j in range(m if n > 0 else 0):
        out = out * _MUL + h[j : j + n]
    return mixed(out)


def least(h: np.ndarray, w: int) -> tuple[np.ndarray, np.ndarray]:
    """Minimum of ``w`` values from each place, and where it is first; by doubling."""
    at, span = np.arange(len(h)), 1
    while span < w:
        step = min(span, w - span)
        left, right = h[: len(h) - step], h[step:]
        at = np.where(left <= right, at[: len(at) - step], at[step:])
        h, span = np.minimum(left, right), span + step
    return h, at


def super_kmers(docs: list[list[bytes]], k: int = K, m: int = M) -> tuple[np.ndarray, ...]:
    """document, first word, number of windows and bucket of each super-k-mer."""
    size = np.array([len(d) for d in docs], np.int64)
    ends = np.cumsum(size)
    n = int(ends[-1]) if len(ends) else 0
    none = np.zeros(0, np.int64)
    if n < k:
        return none, none, none, none
    key, at = least(gram_hashes(word_hashes([w for d in docs for w in d]), m), k - m + 1)
    doc = np.repeat(np.arange(len(docs)), size)
    place = np.flatnonzero(np.arange(n - k + 1) + k <= ends[doc[: n - k + 1]])
    if not len(place):
        return none, none, none, none
    own, where = doc[place], at[place]
    new = np.flatnonzero(np.concatenate([[True], (np.diff(where) != 0) | (np.diff(own) != 0)]))
    first = place[new]
    return own[new], first - (ends - size)[own[new]], np.diff(np.append(new, len(place))), key[first].view(np.int64)


def repeated(strings: list[bytes], k: int) -> list[list[tuple[int, int]]]:
    """For each packed string of one bucket, word ranges that repeated windows cover."""
    cuts: list[list[tuple[int, int]]] = []
    windows: list[bytes] = []
    for s in strings:
        ends = list(accumulate(len(w) + 1 for w in s.split(b" ")))
        cuts.append(own := [(a, b - 1) for a, b in zip([0, *ends], ends[k - 1 :], strict=False)])
        windows += [s[a:b] for a, b in own]
    windows.sort()
    twice = {a for a, b in zip(windows, windows[1:], strict=False) if a == b}
    out = []
    for s, own in zip(strings, cuts, strict=True):
        ranges: list[tuple[int, int]] = []
        for i, (a, b) in enumerate(own) if twice else ():
            if s[a:b] in twice:
                if ranges and ranges[-1][1] >= i:
                    ranges[-1] = (ranges[-1][0], i + k)
                else:
                    ranges.append((i, i + k))
        out.append(ranges)
    return out


def remove_repeats(docs: DataFrame, *, k: int = K, m: int = M, hot: int = HOT, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, [text: the kept words] of every document."""
    rows = docs.select(F.col("`doc_id`"), F.col("`text`")).select("doc_id", "text", F.coalesce("doc_id", F.lit(-(2**63))).alias("did"), F.coalesce(F.xxhash64("text"), F.lit(0)).alias("th"))

    def buckets(batch: pa.RecordBatch) -> pa.RecordBatch:
        doc, _, _, key = super_kmers([t.encode().split() for t in texts(batch)], k, m)
        return pa.RecordBatch.from_arrays([pa.array(key), col(batch, "did").take(pa.array(doc)), col(batch, "th").take(pa.array(doc))], names=["key", "did", "th"])

    found = map_text(rows.select("did", "th", "text"), buckets, "key long, did long, th long")
    shared = materialise(found.groupBy("key").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "substring-buckets")

    def packed(batch: pa.RecordBatch, emit) -> pa.RecordBatch:
        words = [t.encode().split() for t in texts(batch)]
        doc, first, n, key = super_kmers(words, k, m)
        wanted = col(batch, "keys")
        size = np.diff(wanted.offsets.to_numpy())
        pair = np.stack([np.repeat(np.arange(len(words)), size), wanted.flatten().to_numpy()], 1)
        keep = np.isin(np.stack([doc, key], 1).copy().view("i8,i8").ravel(), pair.astype(np.int64).copy().view("i8,i8").ravel())
        doc, first, n, key = doc[keep], first[keep], n[keep], key[keep]
        strings = [b" ".join(words[d][a : a + c + k - 1]) for d, a, c in zip(doc.tolist(), first.tolist(), n.tolist(), strict=True)]
        return emit(key, strings, col(batch, "did").take(pa.array(doc)), col(batch, "th").take(pa.array(doc)), first)

    def whole(key, strings, did, th, first):
        return pa.RecordBatch.from_arrays([pa.array(key), pa.array(strings, pa.binary()), did, th, pa.array(first)], names=["key", "s", "did", "th", "first"])

    def by_document(keys: DataFrame) -> DataFrame:
        own = found.join(keys, "key").groupBy("did", "th").agg(F.collect_set("key").alias("keys"))
        return rows.join(own, ["did", "th"]).select("did", "th", "text", "keys")

    def count(batches):
        held: list[pa.RecordBatch] = []

        def done(upto: pa.Table):
            keys = upto.column("key").to_numpy()
            strings = upto.column("s").to_pylist()
            cuts = [0, *(np.flatnonzero(np.diff(keys)) + 1).tolist(), len(keys)]
            row, a, b = [], [], []
            for x, y in zip(cuts, cuts[1:], strict=False):
                for i, ranges in enumerate(repeated(strings[x:y], k) if y - x > 1 else ()):
                    for p, q in ranges:
                        row.append(x + i), a.append(p), b.append(q)
            row = np.array(row, np.int64)
            first = upto.column("first").to_numpy()[row]
            return pa.RecordBatch.from_arrays([pa.array(upto.column("did").to_numpy()[row]), pa.array(upto.column("th").to_numpy()[row]), pa.array(first + np.array(a, np.int64)), pa.array(first + np.array(b, np.int64))], names=["did", "th", "a", "b"])

        for batch in batches:
            keys = batch.column(0).to_numpy()
            cut = int(np.searchsorted(keys, keys[-1])) if batch.num_rows else 0  # a bucket may go on in the next batch
            if held and batch.num_rows and held[-1].column(0)[-1].as_py() == keys[-1]:
                held.append(batch)
                continue
            if batch.num_rows:
                yield done(pa.Table.from_batches([*held, batch.slice(0, cut)]))
                held = [batch.slice(cut)]
        if held:
            yield done(pa.Table.from_batches(held))

    ranges_schema = "did long, th long, a long, b long"
    cold = by_document(shared.filter(F.col("n") <= hot).select("key"))
    strings = map_text(cold, lambda b: packed(b, whole), "key long, s binary, did long, th long, first long")
    ranges = strings.repartition("key").sortWithinPartitions("key").mapInArrow(count, ranges_schema)
    hot_keys = shared.filter(F.col("n") > hot).select("key")
    if not hot_keys.isEmpty():

        def single(key, strings, did, th, first):
            row, digest, at = [], [], []
            for i, s in enumerate(strings):
                ends = list(accumulate(len(w) + 1 for w in s.split(b" ")))
                for j, (a, b) in enumerate(zip([0, *ends], ends[k - 1 :], strict=False)):
                    row.append(i), digest.append(hashlib.blake2b(s[a : b - 1], digest_size=16).digest()), at.append(j)
            row = np.array(row, np.int64)
            return pa.RecordBatch.from_arrays([pa.array(key[row]), pa.array(digest, pa.binary()), did.take(pa.array(row)), th.take(pa.array(row)), pa.array(first[row] + np.array(at, np.int64))], names=["key", "digest", "did", "th", "a"])

        # one plan, so the texts are shuffled once for all uses; a digest's windows share a bucket, and those of busy buckets are spread
        windows = map_text(by_document(hot_keys), lambda b: packed(b, single), "key long, digest binary, did long, th long, a long")
        busy = F.broadcast(heavy(shared, "key", "n").withColumn("busy", F.lit(True)))
        marked = windows.join(busy, "key", "left").withColumn("busy", F.coalesce("busy", F.lit(False)))
        parts = F.when(F.col("busy"), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
        twice = marked.groupBy("digest").agg(F.count(F.lit(1)).alias("n"), F.max("busy").alias("busy")).filter("n > 1").select("digest", F.explode(parts).alias("salt"))
        salt = F.when(F.col("busy"), F.pmod(F.xxhash64("did", "a"), F.lit(SALTS))).otherwise(0).cast("int")
        met = marked.withColumn("salt", salt).join(twice, ["digest", "salt"], "left_semi")
        ranges = ranges.unionByName(met.select("did", "th", "a", (F.col("a") + k).alias("b")))

    def cut(batch: pa.RecordBatch) -> pa.RecordBatch:
        out = []
        for text, own in zip(texts(batch), col(batch, "ranges").to_pylist(), strict=True):
            words = text.encode().split()
            n = len(words)
            if own:
                edge = np.zeros(n + 1, np.int64)
                for r in own:
                    edge[r["a"]] += 1
                    edge[r["b"]] -= 1
                words = [w for w, c in zip(words, np.cumsum(edge).tolist(), strict=False) if not c]
            kept = b" ".join(words)
            out.append((n, n - len(words), hashlib.sha256(kept).hexdigest(), *([kept.decode()] if with_text else [])))
        arrays = [pa.array(x, t) for x, t in zip(zip(*out, strict=True), [pa.int64(), pa.int64(), pa.string(), pa.string()], strict=False)]
        return pa.RecordBatch.from_arrays([col(batch, "doc_id"), *arrays], names=["doc_id", "n_words", "n_removed", "kept_sha256", "text"][: 1 + len(arrays)])

    own = ranges.groupBy("did", "th").agg(F.collect_set(F.struct("a", "b")).alias("ranges"))
    joined = rows.join(own, ["did", "th"], "left").select("doc_id", "text", "ranges")
    return map_text(joined, cut, "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", text string" * with_text)
