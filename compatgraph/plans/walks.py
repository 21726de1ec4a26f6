"""Neighbour-class counts over several hops, with and without backtracking, and the explicit baselines.

The chain keeps n x k states and never forms a node-by-node matrix; only k x k counts reach the driver.  Counts of up to five hops are read
off the products of states of up to three, so that only two hops go over all edges.
Counts are of paths on the simple graph (weights are ignored).  Counts are BIGINT: they overflow only beyond 9e18, which ANSI mode reports.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.labels import names, one_hot
from .blocks import Blocks, received, sent
from .lineage import cut, small


def _messages(A: DataFrame, N: DataFrame, k: int) -> DataFrame:
    return A.join(N.withColumnRenamed("node", "dst"), "dst").select(F.col("src").alias("node"), *names(k))


def _summed(rows: DataFrame, k: int) -> DataFrame:
    return rows.groupBy("node").agg(*[F.sum(c).alias(c) for c in names(k)])


def neighbor_counts(edges: DataFrame, seeds: DataFrame, k: int) -> DataFrame:
    """N_1: labelled neighbours of each class."""
    return _summed(_messages(edges.select("src", "dst"), one_hot(seeds, k), k), k)


def _degrees(A: DataFrame) -> DataFrame:
    return A.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("deg"))


def _next(A: DataFrame, deg: DataFrame, last: DataFrame, before: DataFrame, l: int, k: int, backtracking: bool) -> DataFrame:
    """N_l from the two states before it: messages and echo are summed in one aggregation."""
    rows = _messages(A, last, k)
    if not backtracking:
        factor = F.col("deg") if l == 2 else F.col("deg") - 1
        rows = rows.unionByName(before.join(deg, "node").select("node", *[(-factor * F.col(c)).alias(c) for c in names(k)]))
    return _summed(rows, k)


def hop_counts(edges: DataFrame, seeds: DataFrame, k: int, lmax: int, backtracking: bool = False) -> list[DataFrame]:
    """N_1 .. N_lmax.  Without backtracking: N_2 = A N_1 - D X and N_l = A N_(l-1) - (D - I) N_(l-2)."""
    A = edges.select("src", "dst")
    deg = _degrees(A)
    states = [one_hot(seeds, k), neighbor_counts(edges, seeds, k)]
    for l in range(2, lmax + 1):
        states.append(_next(A, deg, states[-1], states[-2], l, k, backtracking))
    return states[1:]


def pair_counts(N: DataFrame, seeds: DataFrame, k: int) -> DataFrame:
    """c, d, cnt for all k x k pairs: X'N."""
    sums = seeds.join(N, "node").groupBy(F.col("cls").alias("c")).agg(*[F.sum(x).alias(x) for x in names(k)])
    flat = sums.select("c", F.explode(F.array(*[F.struct(F.lit(d).alias("d"), F.col(f"b{d}").alias("cnt")) for d in range(k)])).alias("p")).select("c", "p.d", "p.cnt")
    grid = N.sparkSession.range(k).select(F.col("id").cast("int").alias("c")).withColumn("d", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    return grid.join(flat, ["c", "d"], "left").select("c", "d", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


def one_hop_matrix(edges: DataFrame, seeds: DataFrame, k: int) -> np.ndarray:
    """M_1: only edges between seeds matter, so the edges meet the seeds on both sides and nothing else is moved."""
    near = small(seeds)
    c, d = near.select(F.col("node").alias("src"), F.col("cls").alias("c")), near.select(F.col("node").alias("dst"), F.col("cls").alias("d"))
    M = np.zeros((k, k))
    for r in edges.select("src", "dst").join(d, "dst").join(c, "src").groupBy("c", "d").agg(F.count(F.lit(1)).alias("n")).collect():
        M[r.c, r.d] = r.n
    return M


#: M_l as sums of products (sign, a, b, w): N_a' W N_b with N_0 = X and W a power of the degrees D: "" I, "d" D, "d1" D - I, "d2" D - 2I.
#: N_a' N_b counts walks of a + b hops that don't turn back but perhaps where both meet; those that do are counted by the other terms.
_TURNLESS = {
    1: [(1, 0, 1, "")],
    2: [(1, 1, 1, ""), (-1, 0, 0, "d")],
    3: [(1, 1, 2, ""), (-1, 0, 1, "d1")],
    4: [(1, 2, 2, ""), (-1, 1, 1, "d2"), (-1, 0, 0, "d")],
    5: [(1, 2, 3, ""), (-1, 1, 2, "d2"), (-1, 0, 1, "d1")],
}


def _products(l: int, backtracking: bool) -> list[tuple[int, int, int, str]]:
    if backtracking:
        return [(1, l // 2, l - l // 2, "")]
    return _TURNLESS.get(l, [(1, 0, l, "")])


def _all_products(states: list[DataFrame], deg: DataFrame, k: int, wanted: set, groups: list[list[int]]) -> dict:
    """N_a' W N_b for each wanted (a, b, w), of the classes within each group: one row by node, then one aggregation."""
    used = sorted({i for a, b, _ in wanted for i in (a, b)})
    parts = [states[i].select("node", *[(F.col(c) if i == j else F.lit(0).cast("long")).alias(f"n{j}_{c}") for j in used for c in names(k)], F.lit(0).cast("long").alias("deg")) for i in used]
    if any(w for _, _, w in wanted):
        parts.append(deg.select("node", *[F.lit(0).cast("long").alias(f"n{j}_{c}") for j in used for c in names(k)], F.col("deg")))
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    wide = both.groupBy("node").agg(*[F.sum(c).alias(c) for c in both.columns[1:]])
    factor = {"": None, "d": F.col("deg"), "d1": F.col("deg") - 1, "d2": F.col("deg") - 2}
    keys = [(*p, c, d) for p in sorted(wanted) for g in groups for c in g for d in g]
    term = lambda a, b, w, c, d: F.col(f"n{a}_b{c}") * F.col(f"n{b}_b{d}") * (F.lit(1) if factor[w] is None else factor[w])
    row = wide.agg(*[F.sum(term(*x)).alias(f"p{i}") for i, x in enumerate(keys)]).first()
    out = {p: np.zeros((k, k)) for p in wanted}
    for (a, b, w, c, d), v in zip(keys, row, strict=True):
        out[a, b, w][c, d] = v or 0
    return out


def count_matrices(edges: DataFrame, seeds: DataFrame, k: int, lmax: int, backtracking: bool = False, groups: list[list[int]] | None = None, held: Blocks | None = None) -> list[np.ndarray]:
    """M_1 .. M_lmax on the driver: k x k numbers a hop.  Callers that count on one graph again hold its edges cached or bucketed by ``dst``,
    or in blocks, which the hops then go over (``held``, with all seeds as nodes).

    Several sets of seeds go together as classes of their own (``batch_seeds``): ``groups`` then says which classes belong together.
    """
    if lmax == 1 and groups is None:
        return [one_hop_matrix(edges, seeds, k)]
    A = edges.select("src", "dst")
    wanted = {p[1:] for l in range(1, lmax + 1) for p in _products(l, backtracking)}
    if held is not None:
        found = _block_products(held, seeds, k, wanted, backtracking, groups or [list(range(k))])
        return [sum(sign * found[a, b, w] for sign, a, b, w in _products(l, backtracking)) for l in range(1, lmax + 1)]
    deg = _degrees(A).persist()
    X = one_hot(seeds, k)
    first = A.join(small(seeds).withColumnRenamed("node", "dst"), "dst").groupBy(F.col("src").alias("node")).agg(*[F.sum((F.col("cls") == c).cast("long")).alias(n) for c, n in enumerate(names(k))])
    states = [X, first.persist()]
    for l in range(2, max(b for _, b, _ in wanted) + 1):
        states.append(_next(A, deg, states[-1], states[-2], l, k, backtracking).persist())
    found = _all_products(states, deg, k, wanted, groups or [list(range(k))])
    for df in [deg, *states[1:]]:
        df.unpersist()
    return [sum(sign * found[a, b, w] for sign, a, b, w in _products(l, backtracking)) for l in range(1, lmax + 1)]


def _block_products(held: Blocks, seeds: DataFrame, k: int, wanted: set, backtracking: bool, groups: list[list[int]]) -> dict:
    """``_all_products`` with the hops going over blocks: each part adds up its nodes' products, and these sums reach the driver."""
    hops = max(b for _, b, _ in wanted)

    def step(piece: dict, letters: list, i: int):
        """Takes in N_i and sends it on for N_(i+1); N_0 is what the seeds say."""
        n = len(piece["nodes"])
        if i == 0:
            N = [np.zeros((k, n), np.int64)]
            for nodes, cls in letters:
                at = np.minimum(np.searchsorted(piece["nodes"], nodes), n - 1)
                if (piece["nodes"][at] != nodes).any():
                    raise ValueError("there are seeds that the blocks do not hold")
                N[0][cls, at] = 1
            deg = None
        else:
            N, deg = next(x[1] for x in letters if x[0] == "state")
            y = whole(received(piece, letters, k + (i == 1)))
            deg = y[k] if i == 1 else deg
            N.append(y[:k] if backtracking or i == 1 else y[:k] - (deg if i == 2 else deg - 1) * N[i - 2])
        if i < hops:
            yield piece["part"], ("state", (N, deg))
            yield from sent(piece, [*N[i].astype(float), *([np.ones(n)] if i == 0 else [])], [0] * (k + (i == 0)))
        else:
            factor = {"": 1, "d": deg, "d1": deg - 1, "d2": deg - 2}
            yield piece["part"], ("told", {(a, b, w, *g): whole((N[a][g] * factor[w]).astype(float) @ N[b][g].T.astype(float), N[a][g] * factor[w], N[b][g]) for a, b, w in sorted(wanted) for g in groups})

    mail = held.deal(seeds.filter(F.col("cls").between(0, k - 1)).select("node", "cls"))
    for i in range(hops + 1):
        mail = held.round(mail, lambda piece, letters, i=i: step(piece, letters, i))
    out = {p: np.zeros((k, k)) for p in wanted}
    exact: dict = {}
    for x in mail.map(lambda x: x[1][1]).collect():  # k x k numbers a part
        for of, M in x.items():
            exact[of] = exact.get(of, 0) + M.astype(object)
    for (a, b, w, *g), M in exact.items():
        out[a, b, w][np.ix_(g, g)] = M.astype(float)
    return out


def whole(x: np.ndarray, *factors: np.ndarray) -> np.ndarray:
    """``x`` in whole numbers, or the whole product of two ``factors`` whose size it tells; an error where these would not be exact."""
    if np.abs(x).max(initial=0) > (2**62 if factors else 2**53):
        raise OverflowError("counts are too large to be exact")
    return np.einsum("cn,dn->cd", *factors) if factors else np.rint(x).astype(np.int64)


def batch_seeds(sets: list[DataFrame], k: int) -> tuple[DataFrame, list[list[int]]]:
    """Several sets of seeds as one, with classes of their own for each, and the groups for ``count_matrices``: one pass serves all."""
    both = None
    for i, x in enumerate(sets):
        own = x.select("node", (F.col("cls") + i * k).alias("cls"))
        both = own if both is None else both.unionByName(own)
    return both, [list(range(i * k, (i + 1) * k)) for i in range(len(sets))]


def batched_matrices(edges: DataFrame, sets: list[DataFrame], k: int, lmax: int, backtracking: bool = False, held: Blocks | None = None) -> list[list[np.ndarray]]:
    """For each set of seeds its M_1 .. M_lmax, all from one pass over the graph a hop."""
    seeds, groups = batch_seeds(sets, k)
    found = count_matrices(edges, seeds, k * len(sets), lmax, backtracking, groups, held)
    return [[M[np.ix_(g, g)] for M in found] for g in groups]


def pairs_available(edges: DataFrame, seeds: DataFrame, k: int, lmax: int, backtracking: bool = False) -> list[int]:
    """Labelled pairs that each hop offers to the estimators: the sums of M_1 .. M_lmax."""
    return [int(M.sum()) for M in count_matrices(edges, seeds, k, lmax, backtracking)]


def path_matrix(edges: DataFrame, l: int) -> DataFrame:
    """Entries (src, dst, n) of A^l: the baseline that grows by the degree with each hop."""
    if l > 3:
        raise ValueError("explicit path matrices are a baseline for at most 3 hops")
    A = edges.select("src", "dst")
    out = A.withColumn("n", F.lit(1).cast("long"))
    for _ in range(l - 1):
        out = out.join(A.select(F.col("src").alias("dst"), F.col("dst").alias("to")), "dst").groupBy("src", F.col("to").alias("dst")).agg(F.sum("n").alias("n"))
    return out


def nb_path_matrix(edges: DataFrame, l: int) -> DataFrame:
    """Non-backtracking paths: A, A^2 - D, A^3 - (D A + A D - A)."""
    A = edges.select("src", "dst")
    if l == 1:
        return A.withColumn("n", F.lit(1).cast("long"))
    deg = A.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    if l == 2:
        less = deg.select("src", F.col("src").alias("dst"), (-F.col("deg")).alias("n"))
    else:
        less = A.join(deg, "src").join(deg.select(F.col("src").alias("dst"), F.col("deg").alias("there")), "dst").select("src", "dst", (1 - F.col("deg") - F.col("there")).alias("n"))
    return path_matrix(edges, l).unionByName(less).groupBy("src", "dst").agg(F.sum("n").alias("n")).filter("n <> 0")


def enumerate_walks(edges: DataFrame, l: int, backtracking: bool = False) -> DataFrame:
    """src, dst, n by walking edge by edge; ``next <> previous`` without backtracking.  Ground truth for small graphs.

    Before the last hop only edges that lead on are walked: what ends at a node with no way but back is part of no walk of ``l`` hops.
    So a star's leaves don't meet each other.
    """
    steps = edges.select(F.col("src").alias("at"), F.col("dst").alias("next"))
    onward = steps
    if l > 1:
        ways = edges.groupBy(F.col("src").alias("next")).agg(F.min("dst").alias("low"), F.max("dst").alias("high"))
        onward = steps.join(ways, "next").filter(F.lit(True) if backtracking else (F.col("low") != F.col("at")) | (F.col("high") != F.col("at"))).select("at", "next")
    walk = onward.select(F.col("at").alias("start"), F.col("at").alias("prev"), F.col("next").alias("at"))
    for i in range(2, l + 1):
        nxt = onward if i < l else steps
        walk = walk.join(nxt, "at").filter(F.lit(True) if backtracking else F.col("next") != F.col("prev")).select("start", F.col("at").alias("prev"), F.col("next").alias("at"))
    return walk.groupBy(F.col("start").alias("src"), F.col("at").alias("dst")).agg(F.count(F.lit(1)).alias("n"))


def weighted_hop_counts(edges: DataFrame, seeds: DataFrame, k: int, lmax: int) -> list[DataFrame]:
    """N_1 .. N_lmax of non-backtracking walks on a weighted graph, each walk counted by the product of its weights.

    The n x k recurrence holds for simple graphs only.  Here the state is per ordered edge: what starts over (i, j) is w_ij times
    all that starts at j, less what starts there over (j, i).  A hop is two joins and one aggregation, 2m rows of k columns.
    """
    cols, E = names(k), edges.repartition("dst").persist()
    zero = [F.coalesce(c, F.lit(0)) for c in cols]
    over = E.join(one_hot(seeds, k).withColumnRenamed("node", "dst"), "dst", "left").select("src", "dst", *[(F.col("w") * z).alias(c) for c, z in zip(cols, zero, strict=True)])
    out = []
    for l in range(1, lmax + 1):
        if l > 1:
            back = over.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *[F.col(c).alias(f"r{i}") for i, c in enumerate(cols)])
            ahead = E.join(out[-1].withColumnRenamed("node", "dst"), "dst").join(back, ["src", "dst"])
            over = cut(ahead.select("src", "dst", *[(F.col("w") * (F.col(c) - F.col(f"r{i}"))).alias(c) for i, c in enumerate(cols)]))
        out.append(over.groupBy(F.col("src").alias("node")).agg(*[F.sum(c).alias(c) for c in cols]))
    E.unpersist()
    return out
