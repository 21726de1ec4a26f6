"""Byte-level BPE encoding and decoding with DuckDB recursive queries inside each partition.

Distinct pre-token pieces become (word, position, token) rows.  A recursive query joins each
adjacent pair to the merge table and contracts every word's leftmost minimum-rank pair until no
pair of a word is left; an ordered aggregation turns ids back into bytes.  Pieces are looked up
in a bounded cache per Python worker, so a piece is contracted about once per task.

Null texts count as empty (no tokens, empty decoding); repeated rows give repeated results; other
columns are ignored, and an empty table gives an empty result.  A round of the recursion handles all rows of a batch, so a batch holds words of
like length and ``ROUND_BYTES`` bytes at most, or one word.  A word needs a round for each contraction, which makes the recursion quadratic in
its bytes; a piece longer than ``LONG_PIECE`` bytes is contracted by the same rule with a heap instead.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from .common import KEPT, Recent, col, map_text, narrow, texts

LONG_PIECE, ROUND_BYTES = 1_024, 512 << 10
#: Pieces in a generation of a worker's cache: a bound on memory, never on what is encoded.
CACHE_PIECES = 400_000

ENCODE_SQL = """
with recursive st(w, p, t, live) as (
  select w, p, t, true from sym
  union all
  (with seq as (select w, p, t, lead(t) over q as nt, lead(p) over q as np from st where live
                window q as (partition by w order by p)),
        pairs as (select s.w, s.p, s.t, s.np, m.k from seq s left join merges m on m.pr = ((s.t::bigint << 20) | s.nt)),
        best as (select w, min((k::bigint << 32) | p) as b, arg_min(np, (k::bigint << 32) | p) as gone
                 from pairs where k is not null group by w)
   select pairs.w, p, case when (best.b & 4294967295) = p then (best.b >> 32)::int else t end, best.w is not null
   from pairs left join best using (w) where p is distinct from gone)
)
select w, list(t order by p) as ids from st where not live group by w order by w
"""
DECODE_SQL = "select g, string_agg(h, '' order by p) as h from ids join vocab using (t) group by g"


def read_ranks(path: str) -> dict[bytes, int]:
    """Ranks of a tiktoken vocabulary file: a base64 token and its rank on each line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class Coder:
    """Encoder and decoder of one vocabulary inside one Python worker."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import duckdb
        import regex

        self.split, self.ranks = regex.compile(pattern).findall, ranks
        self.byte = [ranks[bytes([i])] for i in range(256)]
        self.con = duckdb.connect(config={"threads": 1, "memory_limit": "400MB", "temp_directory": ""})  # batches are bounded, nothing spills
        pairs = [(ranks[b[:i]] << 20 | ranks[b[i:]], k) for b, k in ranks.items() for i in range(1, len(b)) if b[:i] in ranks and b[i:] in ranks]
        self.con.register("pairs_in", pa.table({"pr": [p for p, _ in pairs], "k": pa.array([k for _, k in pairs], pa.int32())}))
        self.con.register("vocab_in", pa.table({"t": pa.array(list(ranks.values()), pa.int32()), "h": [b.hex() for b in ranks]}))
        self.con.execute("create table merges as select * from pairs_in; create table vocab as select * from vocab_in")
        self.cache = Recent(CACHE_PIECES)

    def learn(self, pieces: set[str]) -> dict[str, tuple[str, bytes]]:
        """The written ids and the decoded bytes of pieces, encoding and decoding those that the cache lacks."""
        new = self.cache.missing(pieces)
        if not new:
            return self.cache.young
        found: dict[str, list[int]] = {}
        rows: list[tuple[str, bytes]] = []
        for piece in new:
            raw = piece.encode()
            if raw in self.ranks:
                found[piece] = [self.ranks[raw]]
            elif len(raw) > LONG_PIECE:
                found[piece] = self.heap(raw)
            else:
                rows.append((piece, raw))
        rows.sort(key=lambda r: len(r[1]))
        ends = np.cumsum([len(b) for _, b in rows])
        i = 0
        while i < len(rows):
            done = int(ends[i]) - len(rows[i][1])
            j = max(i + 1, int(np.searchsorted(ends, done + ROUND_BYTES, "right")))
            part, i = rows[i:j], j
            found.update(zip((p for p, _ in part), self.contract([b for _, b in part]), strict=True))
        back = self.decode(list(found.values()))
        self.cache.young.update((p, (" ".join(map(str, ids)), raw)) for (p, ids), raw in zip(found.items(), back, strict=True))
        return self.cache.young

    def contract(self, words: list[bytes]) -> list[list[int]]:
        size = np.array([len(w) for w in words])
        flat = np.frombuffer(b"".join(words), np.uint8)
        first = np.cumsum(size) - size
        self.con.register("sym", pa.table({"w": np.repeat(np.arange(len(words), dtype=np.int32), size), "p": (np.arange(len(flat)) - np.repeat(first, size)).astype(np.int32), "t": np.array(self.byte, np.int32)[flat]}))
        out = self.con.sql(ENCODE_SQL).to_arrow_table()
        self.con.unregister("sym")
        return out.column("ids").to_pylist()

    def heap(self, raw: bytes) -> list[int]:
        """The same contraction order for one long piece: a heap of (rank, position) over a linked list."""
        tok, nxt, prv = [raw[i : i + 1] for i in range(len(raw))], list(range(1, len(raw) + 1)), list(range(-1, len(raw) - 1))
        best = [(k, i, tok[i], tok[i + 1]) for i in range(len(raw) - 1) if (k := self.ranks.get(tok[i] + tok[i + 1])) is not None]
        heapq.heapify(best)
        while best:
            _, i, a, b = heapq.heappop(best)
            j = nxt[i] if tok[i] else len(raw)
            if tok[i] != a or j >= len(raw) or tok[j] != b:
                continue
            tok[i], tok[j], nxt[i] = a + b, b"", nxt[j]
            if nxt[i] < len(raw):
                prv[nxt[i]] = i
            for x in (prv[i], i):
                if x >= 0 and nxt[x] < len(raw) and (k := self.ranks.get(tok[x] + tok[nxt[x]])) is not None:
                    heapq.heappush(best, (k, x, tok[x], tok[nxt[x]]))
        return [self.ranks[t] for t in tok if t]

    def decode(self, groups: list[list[int]]) -> list[bytes]:
        """Bytes of each list of ids, by an ordered aggregation."""
        size = np.array([len(g) for g in groups], np.int64)
        flat = np.fromiter(chain.from_iterable(groups), np.int32, int(size.sum()))
        self.con.register("ids", pa.table({"g": np.repeat(np.arange(len(groups), dtype=np.int32), size), "p": np.arange(len(flat)), "t": flat}))
        out = self.con.sql(DECODE_SQL).to_arrow_table()
        self.con.unregister("ids")
        found = dict(zip(out.column("g").to_pylist(), out.column("h").to_pylist(), strict=True))
        return [bytes.fromhex(found.get(i, "")) for i in range(len(groups))]


def coder(key: str, shared, pattern: str) -> Coder:
    """The worker's coder of a vocabulary, kept between tasks until the worker gets one of another operator or vocabulary."""
    if key not in KEPT:
        KEPT.clear()
        KEPT[key] = Coder(shared.value, pattern)
    return KEPT[key]


def _shared(docs: DataFrame, path: str, pattern: str):
    """The vocabulary is read by the driver and broadcast: its size is that of the file, whatever the input."""
    ranks = read_ranks(path)
    key = hashlib.sha256(repr((sorted(ranks.items()), pattern)).encode()).hexdigest()
    return key, docs.sparkSession.sparkContext.broadcast(ranks)


def encode(docs: DataFrame, path: str, pattern: str, *, with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, [ids array<int>], ids_sha256, decoded_sha256 of every document."""
    key, shared = _shared(docs, path, pattern)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        c = coder(key, shared, pattern)
        pieces = [c.split(t) for t in texts(batch)]
        known = c.learn(set().union(*pieces)).__getitem__
        written, back = [], []
        for p in pieces:
            ids, raw = zip(*map(known, p), strict=True) if p else ((), ())
            written.append(" ".join(ids))
            back.append(hashlib.sha256(b"".join(raw)).hexdigest())
        out = [col(batch, "doc_id"), pa.array([s.count(" ") + 1 if s else 0 for s in written], pa.int64())]
        if with_ids:
            out.append(pa.array([np.fromstring(s, np.int32, sep=" ") for s in written], pa.list_(pa.int32())))
        out += [pa.array([hashlib.sha256(s.encode()).hexdigest() for s in written]), pa.array(back)]
        return pa.RecordBatch.from_arrays(out, names=names)

    names = ["doc_id", "n_tokens", *(["ids"] if with_ids else []), "ids_sha256", "decoded_sha256"]
    return map_text(narrow(docs, "doc_id", "text"), run, "doc_id long, n_tokens long, " + "ids array<int>, " * with_ids + "ids_sha256 string, decoded_sha256 string", keeps=key)


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, text of every row of (doc_id, ids); a null or empty list is the empty text."""
    key, shared = _shared(encoded, path, pattern)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        ids = pc.fill_null(col(batch, "ids"), [])
        back = coder(key, shared, pattern).decode(ids.to_pylist())
        return pa.RecordBatch.from_arrays([col(batch, "doc_id"), pa.array([b.decode("utf-8", "replace") for b in back])], names=["doc_id", "text"])

    return map_text(narrow(encoded, "doc_id", "ids"), run, "doc_id long, text string", "ids", key)
