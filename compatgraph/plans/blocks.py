"""A graph in blocks of arrays, for loops that send states along the same edges many times.

A node belongs to the part that its number hashes to, and an edge to the part of its ``dst``.  A part holds its nodes and edges as arrays
(8 bytes an edge, 16 with weights), placed once; a round multiplies them with the states of the part's nodes, adds up by ``src`` and
mails one array a pair of parts, of no more numbers than there are edges.  So a round is one stage with one exchange, no row is hashed, sorted
or joined again, and parts grow in number, not in size, with the graph.  Nothing but sums of a part reaches the driver.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import RDD, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .lineage import cut, shared_dir

#: Edges of a part: about so many at most, and not much fewer than so many where cores would be idle else.
MOST, LEAST = 1 << 21, 1 << 15
#: Rows that are dealt out at a time, rounds between two checkpoints of the mail.
DEALT, CUT = 1 << 20, 10


def place(part: int) -> int:
    """The partition of a part.  One function for all exchanges: with it blocks and mail meet without another one."""
    return part


def part_of(nodes: np.ndarray, n: int) -> np.ndarray:
    return ((nodes.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(n)


class Blocks:
    """The parts (number, piece) of a graph, kept in memory or on disk until ``drop``."""

    def __init__(self, edges: DataFrame, nodes: DataFrame | None = None):
        """Of edges with ``src``, ``dst`` and ``w`` (whole numbers as nodes), and of ``nodes`` that may have none."""
        self.spark = edges.sparkSession
        edges = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.coalesce(F.col("w").cast("double"), F.lit(0.0)).alias("w")).filter("src is not null and dst is not null")
        m = edges.count()
        self.n = n = max(1, math.ceil(m / MOST), min(self.spark.sparkContext.defaultParallelism, m // LEAST))
        dealt = edges.mapInArrow(lambda rows: _deal(rows, n, "dst"), "part int, src binary, dst binary, w binary")
        mail = dealt.rdd.map(lambda x: (x.part, ("edges", np.frombuffer(x.src, "i8"), np.frombuffer(x.dst, "i8"), np.frombuffer(x.w, "f8"))))
        if nodes is not None:
            own = nodes.select(F.col("node").cast("long")).filter("node is not null").distinct()
            mail = mail.union(own.mapInArrow(lambda rows: _deal(rows, n, "node"), "part int, node binary").rdd.map(lambda x: (x.part, ("nodes", np.frombuffer(x.node, "i8")))))
        met = mail.partitionBy(n, place).mapPartitions(lambda it: _sort(it, n))
        self.rdd = met.partitionBy(n, place).mapPartitions(_tie).partitionBy(n, place).persist(StorageLevel.MEMORY_AND_DISK)

    def drop(self) -> None:
        self.rdd.unpersist()

    def deal(self, rows: DataFrame) -> RDD:
        """(part, (tag, columns)) of rows (node, tag, whole numbers ..), for ``start``."""
        n, names = self.n, rows.columns
        dealt = rows.select(*[F.col(c).cast("long") for c in names]).mapInArrow(lambda x: _deal(x, n, "node"), f"part int, {', '.join(f'{c} binary' for c in names)}")
        return dealt.rdd.map(lambda x: (x.part, [np.frombuffer(x[c], "i8") for c in names])).partitionBy(n, place)

    def round(self, mail: RDD | None, work: Callable) -> RDD:
        """``work(piece, letters)`` of each part yields (part, letter): the mail for the next round."""
        both = self.rdd if mail is None else self.rdd.union(mail)
        return both.mapPartitions(lambda it: _work(it, work)).partitionBy(self.n, place)

    def cut(self, mail: RDD, tell: Callable) -> tuple[RDD, list]:
        """The mail, computed and checkpointed, and ``tell(letter)`` of its letters where that is not None."""
        sc = self.spark.sparkContext
        if sc.getCheckpointDir() is None:
            sc.setCheckpointDir(shared_dir(self.spark))
        mail.persist(StorageLevel.MEMORY_AND_DISK).checkpoint()
        return mail, mail.map(lambda x: tell(x[1])).filter(lambda x: x is not None).collect()

    def frame(self, mail: RDD, schema: str) -> DataFrame:
        """Rows of letters that are Arrow streams."""
        raw = self.spark.createDataFrame(mail.map(lambda x: (bytearray(x[1]),)), "block binary", verifySchema=False)
        return cut(raw.mapInArrow(_rows, schema))


def _deal(batches: Iterable[pa.RecordBatch], n: int, by: str) -> Iterator[pa.RecordBatch]:
    """Rows by the part of their column ``by``: a row (part, an array a column) each; weights that are all 1 stay behind."""
    def out(held):
        cols = {c: np.concatenate([b.column(c).to_numpy(zero_copy_only=False) for b in held]) for c in held[0].schema.names}
        part = part_of(cols[by], n)
        order = np.argsort(part, kind="stable")
        at = np.searchsorted(part[order], np.arange(n + 1, dtype=np.uint64))
        there = [p for p in range(n) if at[p] < at[p + 1]]
        if "w" in cols and (cols["w"] == 1).all():
            cols["w"] = None
        found = {c: [b"" if x is None else x[order[at[p] : at[p + 1]]].tobytes() for p in there] for c, x in cols.items()}
        return pa.RecordBatch.from_arrays([pa.array(there, pa.int32()), *[pa.array(x, pa.binary()) for x in found.values()]], ["part", *found])

    held, size = [], 0
    for b in batches:
        held.append(b)
        size += b.num_rows
        if size >= DEALT:
            yield out(held)
            held, size = [], 0
    if size:
        yield out(held)


def _by_part(it: Iterable) -> dict[int, list]:
    by: dict[int, list] = {}
    for p, x in it:
        by.setdefault(p, []).append(x)
    return by


def _sort(it: Iterable, n: int) -> Iterator[tuple]:
    """The edges of a part in the order of their ``src``, part by part, and to each of these parts the nodes it will hear of."""
    for q, xs in _by_part(it).items():
        for x in xs:
            if x[0] == "nodes":
                yield q, x
        xs = [x for x in xs if x[0] == "edges"]
        if not xs:
            continue
        src, dst = (np.concatenate([x[i] for x in xs]) for i in (1, 2))
        w = np.concatenate([x[3] if len(x[3]) else np.ones(len(x[1])) for x in xs]) if any(len(x[3]) for x in xs) else None
        there, at = np.unique(dst, return_inverse=True)
        owner = part_of(src, n)
        order = np.lexsort((src, owner))
        src, at, w = src[order], at[order].astype(np.int32), None if w is None else w[order]
        starts = np.flatnonzero(np.concatenate([[True], src[1:] != src[:-1]]))
        ends = src[starts]
        cuts = np.searchsorted(owner[order][starts], np.arange(n + 1, dtype=np.uint64))
        yield q, ("edges", there, at, starts, cuts, w)
        for p in range(n):
            if cuts[p] < cuts[p + 1]:
                yield p, ("ends", q, ends[cuts[p] : cuts[p + 1]])


def _tie(it: Iterable) -> Iterator[tuple]:
    """The piece of a part: its nodes in order, its edges by places in them, and for each part that mails to it the places of what comes."""
    for p, xs in _by_part(it).items():
        own = next((x for x in xs if x[0] == "edges"), None)
        nodes = np.unique(np.concatenate([x[2] if x[0] == "ends" else x[1] for x in xs]))
        piece = {"part": p, "nodes": nodes, "into": {x[1]: np.searchsorted(nodes, x[2]).astype(np.int32) for x in xs if x[0] == "ends"}}
        if own is not None:
            _, there, at, starts, cuts, w = own
            piece |= {"at": np.searchsorted(nodes, there).astype(np.int32)[at], "starts": starts, "cuts": cuts, "w": w}
        yield p, piece


def _work(it: Iterable, work: Callable) -> Iterator[tuple]:
    pieces, mail = {}, {}
    for p, x in it:
        if isinstance(x, dict) and "nodes" in x:
            pieces[p] = x
        else:
            mail.setdefault(p, []).append(x)
    if mail.keys() - pieces.keys():
        raise ValueError("there are rows of nodes that the blocks do not hold")
    for p, piece in pieces.items():
        yield from work(piece, mail.pop(p, []))


def sent(piece: dict, x: list[np.ndarray], powers: list[int]) -> Iterator[tuple]:
    """Letters of the sums over edges of ``w ** power`` times each of the states ``x`` of the part's nodes."""
    if "at" not in piece:
        return
    sums = []
    for v, power in zip(x, powers, strict=True):
        v = v[piece["at"]]
        if power and piece["w"] is not None:
            v *= piece["w"] ** power
        sums.append(np.add.reduceat(v, piece["starts"]))
    y, cuts = np.array(sums), piece["cuts"]
    for p in np.flatnonzero(cuts[1:] > cuts[:-1]).tolist():
        yield p, ("sums", piece["part"], y[:, cuts[p] : cuts[p + 1]])


def received(piece: dict, letters: list, k: int) -> np.ndarray:
    """k rows with what came for each node of the part."""
    y = np.zeros((k, len(piece["nodes"])))
    for x in sorted((x for x in letters if x[0] == "sums"), key=lambda x: x[1]):  # one order: reruns agree
        y[:, piece["into"][x[1]]] += x[2]
    return y


def stream(columns: dict[str, np.ndarray], masks: dict[str, np.ndarray]) -> bytes:
    """Columns as an Arrow stream; null where a mask says so."""
    batch = pa.RecordBatch.from_arrays([pa.array(x, mask=masks.get(c)) for c, x in columns.items()], list(columns))
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, batch.schema) as writer:
        writer.write_batch(batch)
    return out.getvalue().to_pybytes()


def _rows(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for x in b.column(0):
            yield from pa.ipc.open_stream(x.as_buffer())


def perron(blocks: Blocks, rounds: int, tol: float) -> tuple[float, float]:
    """Perron root by power iteration from a state of ones, and the last relative change of the two-step ratios of norms.

    The state is scaled at each cut; between two cuts its norms are told by the mail.
    """
    def step(piece, letters, i, factor):
        x, told = np.ones(len(piece["nodes"])), []
        if i:
            x = received(piece, letters, 1)[0] * factor
            told = [] if i % CUT == 1 else next(v[1] for v in letters if v[0] == "norms")
            told = told + [float(x @ x)] if i % 2 == 0 else told
        yield piece["part"], ("norms", told)
        if i < rounds:
            yield from sent(piece, [x], [1])

    last, gap, factor, first, mail, held = 0.0, float("inf"), 1.0, True, None, []
    try:
        for i in range(rounds + 1):
            mail = blocks.round(mail, lambda piece, letters, i=i, factor=factor: step(piece, letters, i, factor))
            factor = 1.0
            if not i or i % CUT and i < rounds:
                continue
            mail, told = blocks.cut(mail, lambda x: x[1] if x[0] == "norms" else None)
            held.append(mail)
            base = 1.0
            for x in np.sqrt(np.sum(told, 0)).tolist() if told else [0.0]:
                if not x:
                    return 0.0, 0.0
                now = math.sqrt(x / base)
                last, gap, base = now, abs(now - last) / now, x
                if gap <= tol and not first:
                    return last, gap
                first = False
            factor = 1.0 / base
            if len(held) > 1:
                held.pop(0).unpersist()
    finally:
        for x in held:
            x.unpersist()
    return last, gap
