"""Modulated propagation, its members, the stability limit, energies, PageRank and belief propagation.

A step multiplies the k belief columns by K (a projection), sends them along the edges (one join on ``dst``), and sums messages, seeds
and echo by node in one aggregation with partial sums before its only exchange.  The state is k scalar columns, so sums stay in generated
code; for many classes it is rows of (node, cls, v).  Lineage is cut every ``CUT`` steps, and what a loop has cached is released at its end.
"""

from __future__ import annotations

import warnings

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.compat import center, radius
from ..operators.labels import modulate, names, one_hot, predict, residual, uniform
from ..operators.scaling import COL, RAW, ROW, SYM, clamp_edges, degrees, echo_diagonal, scale_edges
from .blocks import CUT as MAILED
from .blocks import Blocks, perron, received, sent, stream
from .lineage import cut

CUT = 5


def spread_hubs(P: DataFrame, most: int) -> tuple[DataFrame, DataFrame]:
    """P with a salt, and (dst, parts) of the nodes with over ``most`` edges: these are cut into parts of about ``most`` by a hash of ``src``."""
    hubs = P.groupBy("dst").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > most).select("dst", F.ceil(F.col("n") / most).cast("int").alias("parts")).persist()
    salt = F.pmod(F.xxhash64("src"), F.coalesce("parts", F.lit(1))).cast("int")
    return P.join(hubs, "dst", "left").select("src", "dst", "w", salt.alias("salt")), hubs


def messages(P: DataFrame, state: DataFrame, k: int, hubs: DataFrame | None = None, factor: float = 1.0) -> DataFrame:
    """A row for each edge that has a state at its far end; the states of ``hubs`` go to each part of their edges."""
    cols = names(k)
    there = state.withColumnRenamed("node", "dst")
    if hubs is not None:
        there = there.join(hubs, "dst", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
    w = F.col("w") if factor == 1 else F.col("w") * F.lit(factor)
    return P.join(there, ["dst"] if hubs is None else ["dst", "salt"]).select(F.col("src").alias("node"), *[(w * F.col(c)).alias(c) for c in cols])


def summed(parts: list[DataFrame], k: int) -> DataFrame:
    """Rows of all parts, summed by node."""
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    return both.groupBy("node").agg(*[F.sum(c).alias(c) for c in names(k)])


def send(P: DataFrame, state: DataFrame, k: int, hubs: DataFrame | None = None) -> DataFrame:
    """P times the state, over nodes that have a neighbour with a state."""
    return summed([messages(P, state, k, hubs)], k)


def scaled(state: DataFrame, factor, k: int) -> DataFrame:
    return state.select("node", *[(F.col(c) * factor).alias(c) for c in names(k)])


def add(parts: list[tuple[DataFrame, float]], k: int) -> DataFrame:
    """Weighted sum of states: a union and one aggregation by node."""
    return summed([scaled(df, F.lit(factor), k) for df, factor in parts], k)


def step(P: DataFrame, X: DataFrame | None, B: DataFrame, K: np.ndarray, eps: float, Q: DataFrame | None, hubs: DataFrame | None = None) -> DataFrame:
    """X + eps P B K, less eps^2 Q B K^2 where the echo is taken out."""
    k = len(K)
    parts = [messages(P, B.select("node", *modulate(k, K)), k, hubs, eps)]
    if X is not None:
        parts.append(X)
    if Q is not None:
        parts.append(scaled(B.select("node", *modulate(k, K @ K)).join(Q, "node"), F.lit(-eps * eps) * F.col("q"), k))
    return summed(parts, k)


def operator(edges: DataFrame, seeds: DataFrame, alpha: float, beta: float, gamma: float) -> DataFrame:
    return clamp_edges(scale_edges(edges, alpha, beta), seeds, gamma)


def _dominant(apply, v: DataFrame, k: int, rounds: int, tol: float) -> tuple[float, float, DataFrame]:
    """Size of the dominant eigenvalue of a linear map by power iteration, its last relative change, and the vector.

    Two-step ratios of norms, as bipartite graphs carry it with both signs.  One number a round of two steps reaches the driver.
    """
    last, gap, norms = 0.0, float("inf"), 0
    cols = names(k)
    for i in range(rounds):
        v = apply(v)
        if i % 2:
            v = cut(v)
            norm = v.agg(F.sqrt(F.sum(dot(cols, cols)))).first()[0]
            if not norm:
                return 0.0, 0.0, v
            v = scaled(v, F.lit(1.0 / float(norm)), k)
            norms += 1
            now = float(norm) ** 0.5
            gap = abs(now - last) / now
            if norms > 1 and gap <= tol:
                return now, gap, v
            last = now
    return last, gap, v


def _settled(found: tuple[float, float, DataFrame], tol: float, loose: float = 0.02) -> float:
    radius_, gap, _ = found
    if tol and gap > max(loose, tol):
        warnings.warn(f"the power iteration still moves by {gap:.2g} of its value: give more rounds", stacklevel=3)
    return radius_


def spectral_radius(P: DataFrame, rounds: int = 40, tol: float = 1e-4, held: Blocks | None = None) -> float:
    """Perron root of a non-negative matrix; ``tol`` 0 takes all rounds.  Warns if the last round still moved it by over 2 %.

    ``held``: the blocks of P, where a caller has them.
    """
    own = Blocks(P) if held is None else held
    try:
        root, gap = perron(own, rounds, tol)
    finally:
        if held is None:
            own.drop()
    return _settled((root, gap, P), tol)


def _start(P: DataFrame, k: int) -> DataFrame:
    """Hashed residual rows on all nodes: no eigenvector is orthogonal to them but by chance."""
    nodes = P.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    drawn = nodes.select("node", *[(uniform(F.concat_ws(":", "node", F.lit(str(c)))) / F.lit(2.0**32)).alias(x) for c, x in enumerate(names(k))])
    mean = sum((F.col(c) for c in names(k)), F.lit(0.0)) / k
    return drawn.select("node", *[(F.col(c) - mean).alias(c) for c in names(k)])


def operator_radius(P: DataFrame, K: np.ndarray, eps: float, *, echo: bool = True, rounds: int = 40, tol: float = 1e-4, hubs: DataFrame | None = None) -> float:
    """Radius of one whole update on n x k states, B -> eps P B K - [echo] eps^2 Q B K^2, with K centred."""
    Kc = center(K)
    if not np.abs(Kc).max() or not eps:
        return 0.0
    Q = echo_diagonal(P).persist() if echo else None
    try:
        return _settled(_dominant(lambda v: step(P, None, v, Kc, eps, Q, hubs), _start(P, len(K)), len(K), rounds, tol), tol)
    finally:
        if Q is not None:
            Q.unpersist()


def converges(edges: DataFrame, seeds: DataFrame, K: np.ndarray, eps: float, *, alpha=0.0, beta=0.0, gamma=0.0, echo: bool = False, rounds: int = 40) -> bool:
    """Whether the update reaches its fixed point from any start: the radius of the whole update is below 1."""
    P = operator(edges, seeds, alpha, beta, gamma)
    if echo:
        return operator_radius(P, K, eps, rounds=rounds) < 1
    return eps * spectral_radius(P, rounds) * radius(center(K)) < 1


def stability_limit(edges: DataFrame, seeds: DataFrame, K: np.ndarray, *, alpha=0.0, beta=0.0, gamma=0.0, echo: bool = False, halvings: int = 8, rounds: int = 24) -> float:
    """The eps at which the update stops converging: 1 / (radius(P) radius(K centred)).

    Row, column and symmetric scaling have radius 1, and at most 1 when clamped: that bound is used and no pass is made.  With ``echo``
    the update is quadratic in eps: its radius is bracketed from the limit without echo upwards, and the bracket halved ``halvings`` times.
    """
    rho = 1.0 if alpha + beta == 1 else spectral_radius(operator(edges, seeds, alpha, beta, gamma))
    r = rho * radius(center(K))
    limit = 1 / r if r > 1e-12 else float("inf")
    if not echo or np.isinf(limit):
        return limit
    P = operator(edges, seeds, alpha, beta, gamma).persist()
    Q = echo_diagonal(P).persist()
    Kc, v = center(K), _start(P, len(K))

    def reached(eps: float) -> float:
        nonlocal v  # the last vector is the next one's start
        found = _dominant(lambda x: step(P, None, x, Kc, eps, Q), v, len(K), rounds, 1e-3)
        v = found[2] if found[0] else v
        return found[0]

    low, high = 0.0, limit
    while reached(high) < 1:
        low, high = high, high * 1.5
        if high > 100 * limit:
            high = float("inf")
            break
    for _ in range(halvings if np.isfinite(high) else 0):
        middle = (low + high) / 2
        low, high = (middle, high) if reached(middle) < 1 else (low, middle)
    P.unpersist(), Q.unpersist()
    return (low + high) / 2


def propagate(edges: DataFrame, seeds: DataFrame, K: np.ndarray, *, alpha=0.0, beta=0.0, gamma=0.0, eps: float | None = None, s: float | None = None, r: int = 4, echo: bool = False, centred: bool = True, tol: float | None = None, hub_edges: int | None = None, start: DataFrame | None = None, keep: float = 1.0, held: Blocks | None = None) -> DataFrame:
    """node, b0.. after ``r`` updates (or until the largest change is below ``tol``) from residual seeds.

    Give ``eps``, or ``s`` as a share of the stability limit (s > 1 diverges on purpose: few steps are meant).  With ``hub_edges``
    the edges of nodes that have more are cut into parts of about that size, so that no task gets all edges of a hub.  ``start`` is
    another first state, and ``keep`` the share of it that each update adds (the factors of the family's members in the literature).
    ``held`` are the blocks of a symmetric graph: the updates go over them where there are no other options than the family's.
    """
    k = len(K)
    if eps is None:
        eps = (1.0 if s is None else s) * min(stability_limit(edges, seeds, K, alpha=alpha, beta=beta, gamma=gamma, echo=echo), 1e6)
    K = center(K) if centred else K
    if held is not None and centred and tol is None and start is None and keep == 1 and not hub_edges:
        got = propagate_many(edges, [seeds], [{"seeds": 0, "K": K, "eps": eps, "r": r, "alpha": alpha, "beta": beta, "gamma": gamma, "echo": echo}], k, held)
        return got.select("node", *[F.col(f"b0_{c}").alias(f"b{c}") for c in range(k)]).filter("b0 is not null")
    P, kept = operator(edges, seeds, alpha, beta, gamma), []
    Q = echo_diagonal(P) if echo else None
    P, hubs = spread_hubs(P, hub_edges) if hub_edges else (P, None)
    if hubs is not None:
        kept.append(hubs)
    if r > 1:
        by = ["dst", "salt"] if hub_edges else ["dst"]
        P = P.repartition(*by).sortWithinPartitions(*by).persist()  # in the order of the steps' joins
        kept.append(P)
    B = residual(seeds, k) if start is None else start
    X = B if keep == 1 else scaled(B, F.lit(keep), k)
    for i in range(1, r + 1):
        new = step(P, X, B, K, eps, Q, hubs)
        if tol is not None or i % CUT == 0 or i == r and kept:
            new = cut(new)
        if tol is not None:
            gap = add([(new, 1.0), (B, -1.0)], k).agg(F.max(F.greatest(*[F.abs(c) for c in names(k)]) if k > 1 else F.abs("b0"))).first()[0]
            B = new
            if gap is None or gap < tol:
                break
        B = new
    for df in kept:
        df.unpersist()
    return B


def spectral_radii(edges: DataFrame, seeds: DataFrame, gammas: list[float], rounds: int = 40, tol: float = 1e-4) -> list[float]:
    """``spectral_radius`` of the raw matrix clamped by each of ``gammas``, from one power iteration with a column each."""
    k = len(gammas)
    nodes = edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    weak = seeds.select("node").distinct().withColumn("seed", F.lit(1.0))
    facts = cut(nodes.join(weak, "node", "left").select("node", F.coalesce("seed", F.lit(0.0)).alias("seed")))
    v, last, gap, done = facts.select("node", *[F.lit(1.0).alias(c) for c in names(k)]), [0.0] * k, [float("inf")] * k, [False] * k
    for i in range(rounds):
        v = send(edges, v, k).join(facts, "node").select("node", *[(F.col(c) * (1 - F.lit(float(g)) * F.col("seed"))).alias(c) for c, g in zip(names(k), gammas, strict=True)])
        if i % 2:
            v = cut(v)
            norms = [float(x or 0.0) for x in v.agg(*[F.sqrt(F.sum(F.col(c) * F.col(c))) for c in names(k)]).first()]
            v = v.select("node", *[(F.col(c) / F.lit(x or 1.0)).alias(c) for c, x in zip(names(k), norms, strict=True)])
            for j, x in enumerate(norms):
                if not done[j]:
                    now = x**0.5
                    gap[j] = abs(now - last[j]) / now if now else 0.0
                    done[j], last[j] = not now or i > 1 and gap[j] <= tol, now
            if all(done):
                break
    return [_settled((x, g, v), tol) for x, g in zip(last, gap, strict=True)]


def propagate_many(edges: DataFrame, sets: list[DataFrame], runs: list[dict], k: int, held: Blocks | None = None) -> DataFrame:
    """node, s0.. (the class in each of ``sets``), b0_0, b0_1.. (the beliefs of each of ``runs``): runs of ``propagate`` on one symmetric graph, side by side.

    A run has ``seeds`` (a place in ``sets``), ``K``, ``eps`` and ``r``, and may have ``alpha``, ``beta``, ``gamma`` and ``echo``.  Null is no belief.
    The runs share the rounds over the graph's blocks (``held``, with all seeds as nodes, or own ones): scaling and clamping are factors of
    the nodes.  Runs without echo that differ in K, eps and r only share the terms P^i X too: their beliefs are sums of these times (eps K)^i.
    """
    own = Blocks(edges, _union([x.select("node") for x in sets])) if held is None else held
    try:
        mail = own.deal(_union([x.select("node", F.lit(i).alias("set"), "cls") for i, x in enumerate(sets)]))
        steps = ["seeds", "degrees", *(["echo"] if any(x.get("echo") for x in runs) else []), *range(1, max(x["r"] for x in runs) + 1)]
        work = _Many(len(sets), runs, k)
        for i, (now, then) in enumerate(zip(steps, [*steps[1:], None], strict=True)):
            mail = own.round(mail, lambda piece, letters, now=now, then=then: work.step(piece, letters, now, then))
            if i % MAILED == MAILED - 1 and then is not None:
                mail = own.cut(mail, lambda _: None)[0]
        return own.frame(mail, ", ".join(["node long", *[f"s{i} int" for i in range(len(sets))], *[f"b{j}_{c} double" for j in range(len(runs)) for c in range(k)]]))
    finally:
        if held is None:
            own.drop()


def _union(parts: list[DataFrame]) -> DataFrame:
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    return both


class _Many:
    """What a part does in each round of ``propagate_many``.  A state of k classes is an array of k rows over the part's nodes."""

    def __init__(self, sets: int, runs: list[dict], k: int):
        self.sets, self.k = sets, k
        self.runs = [{"alpha": 0.0, "beta": 0.0, "gamma": 0.0, "echo": False} | x | {"K": center(np.asarray(x["K"], float))} for x in runs]
        self.echoes = [j for j, x in enumerate(self.runs) if x["echo"]]
        self.groups: dict[tuple, list[int]] = {}
        for j, x in enumerate(self.runs):
            if not x["echo"]:
                self.groups.setdefault((x["seeds"], float(x["alpha"]), float(x["beta"]), float(x["gamma"])), []).append(j)
        # terms grow with the largest eps K of their runs: held at the size of its beliefs
        self.scale = {g: max(abs(float(self.runs[j]["eps"])) * radius(self.runs[j]["K"]) for j in js) or 1.0 for g, js in self.groups.items()}

    def live(self, i: int) -> tuple[list[tuple], list[int]]:
        return [g for g, js in self.groups.items() if max(self.runs[j]["r"] for j in js) >= i], [j for j in self.echoes if self.runs[j]["r"] >= i]

    @staticmethod
    def power(state: dict, x: float) -> np.ndarray | float:
        """deg^-x; 0 for what has no edges."""
        return np.where(state["any"], np.power(state["deg"], -float(x), where=state["any"], out=np.zeros(len(state["deg"]))), 0.0) if x else 1.0

    def weak(self, state: dict, seeds: int, gamma: float) -> np.ndarray:
        return np.where(state["s"][seeds] >= 0, 1.0 - gamma, 1.0)

    def residual(self, state: dict, seeds: int) -> np.ndarray:
        s = state["s"][seeds]
        return np.array([np.where(s >= 0, (s == c) - 1.0 / self.k, 0.0) for c in range(self.k)])

    def back(self, state: dict, x: dict) -> np.ndarray | float:
        """The factor of a node in the closed echo diagonal."""
        return self.weak(state, x["seeds"], x["gamma"]) * self.power(state, x["alpha"] + x["beta"])

    def step(self, piece: dict, letters: list, now, then):
        n, k, runs = len(piece["nodes"]), self.k, self.runs
        if now == "seeds":
            state = {"s": np.full((self.sets, n), -1, np.int32)}
            for nodes, tag, cls in letters:
                at = np.minimum(np.searchsorted(piece["nodes"], nodes), n - 1)
                if (piece["nodes"][at] != nodes).any():
                    raise ValueError("there are seeds that the blocks do not hold")
                state["s"][tag, at] = cls
        else:
            state = next(x[1] for x in letters if x[0] == "state")
        if now == "degrees":
            y = received(piece, letters, 2)
            state |= {"deg": y[0], "any": y[1] > 0, "near": np.where(state["s"] >= 0, 0, np.iinfo(np.int32).max), "q": {}}
            state["b"] = {j: self.residual(state, x["seeds"]) for j, x in enumerate(runs)}
            state["t"] = {g: self.residual(state, g[0]) for g in self.groups}
        elif now == "echo":
            y = received(piece, letters, len(self.echoes))
            state["q"] = {j: q * self.back(state, runs[j]) for j, q in zip(self.echoes, y, strict=True)}
        elif now != "seeds":
            self.update(state, received(piece, letters, self.sets + k * sum(map(len, self.live(now)))), now)
        if then is None:
            none = {j: state["near"][x["seeds"]] > x["r"] for j, x in enumerate(runs)}
            found = {"node": piece["nodes"]} | {f"s{i}": s for i, s in enumerate(state["s"])} | {f"b{j}_{c}": b[c] for j, b in sorted(state["b"].items()) for c in range(k)}
            yield piece["part"], stream(found, {f"s{i}": s < 0 for i, s in enumerate(state["s"])} | {f"b{j}_{c}": none[j] for j in none for c in range(k)})
            return
        yield piece["part"], ("state", state)
        if then == "degrees":
            yield from sent(piece, [np.ones(n)] * 2, [1, 0])
        elif then == "echo":
            yield from sent(piece, [self.back(state, runs[j]) * np.ones(n) for j in self.echoes], [2] * len(self.echoes))
        else:
            groups, echoes = self.live(then)
            x = [(s < then).astype(float) for s in state["near"]]
            for g in groups:
                x += list(state["t"][g] * self.power(state, g[2]))
            for j in echoes:
                x += list(float(runs[j]["eps"]) * (runs[j]["K"].T @ state["b"][j]) * self.power(state, runs[j]["beta"]))
            yield from sent(piece, x, [0] * self.sets + [1] * (len(x) - self.sets))

    def update(self, state: dict, y: np.ndarray, i: int) -> None:
        k, runs = self.k, self.runs
        groups, echoes = self.live(i)
        state["near"] = np.minimum(state["near"], np.where(y[: self.sets] > 0, i, np.iinfo(np.int32).max))
        came = iter([y[a : a + k] for a in range(self.sets, len(y), k)])
        for g in groups:
            seeds, alpha, _, gamma = g
            state["t"][g] = next(came) * (self.weak(state, seeds, gamma) * self.power(state, alpha) * self.scale[g])
            for j in self.groups[g]:
                if runs[j]["r"] >= i:
                    state["b"][j] = state["b"][j] + np.linalg.matrix_power(runs[j]["K"] * (float(runs[j]["eps"]) / self.scale[g]), i).T @ state["t"][g]
        for j in echoes:
            x = runs[j]
            less = float(x["eps"]) ** 2 * state["q"][j] * ((x["K"] @ x["K"]).T @ state["b"][j])
            state["b"][j] = next(came) * (self.weak(state, x["seeds"], x["gamma"]) * self.power(state, x["alpha"])) + self.residual(state, x["seeds"]) - less


def propagate_narrow(edges: DataFrame, seeds: DataFrame, K: DataFrame, k: int, *, alpha=0.0, beta=0.0, gamma=0.0, eps: float = 0.1, r: int = 4) -> DataFrame:
    """node, cls, v: the update for many classes, where k columns would be too wide.

    ``K`` is a table (c, d, v) of centred entries, k x k rows at most, zeros left out; a row's residual has all k classes.
    """
    P = operator(edges, seeds, alpha, beta, gamma).repartition("dst").persist()
    X = seeds.select("node", "cls", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("c")).select("node", F.col("c").alias("cls"), ((F.col("cls") == F.col("c")).cast("double") - 1.0 / k).alias("v"))
    table = F.broadcast(K.select(F.col("c").alias("cls"), "d", (F.col("v") * F.lit(eps)).alias("x")))
    B = X
    for i in range(1, r + 1):
        turned = B.join(table, "cls").groupBy("node", "d").agg(F.sum(F.col("v") * F.col("x")).alias("v"))
        sent = P.join(turned.withColumnRenamed("node", "dst"), "dst").select(F.col("src").alias("node"), F.col("d").alias("cls"), (F.col("w") * F.col("v")).alias("v"))
        B = sent.unionByName(X).groupBy("node", "cls").agg(F.sum("v").alias("v"))
        B = cut(B) if i % CUT == 0 or i == r else B
    P.unpersist()
    return B


def members() -> dict[str, dict]:
    """Settings of the named members of the family; ``identity`` ones take K = I."""
    a = lambda scale, gamma=0.0, **more: {"alpha": scale[0], "beta": scale[1], "gamma": gamma, **more}
    return {
        "linear": a(RAW), "linear_echo": a(RAW, echo=True), "hf": a(ROW, 1.0, identity=True), "hf_compat": a(ROW, 1.0), "hf_soft_compat": a(ROW),
        "lnp": a(ROW, identity=True), "lnp_compat": a(ROW), "lgc": a(SYM, identity=True), "lgc_compat": a(SYM), "mrw": a(COL, identity=True), "mrw_compat": a(COL),
        "rnc": a(RAW, identity=True), "hard_linear": a(RAW, 1.0), "recommended": a(COL, 0.5), "grid_row_half": a(ROW, 0.5), "grid_sym_hard": a(SYM, 1.0), "grid_col_hard": a(COL, 1.0), "grid_sym_half": a(SYM, 0.5),
    }


def member(name: str, edges: DataFrame, seeds: DataFrame, K: np.ndarray, **options) -> DataFrame:
    own = dict(members()[name])
    return propagate(edges, seeds, np.eye(len(K)) if own.pop("identity", False) else K, **own, **options)


def _plain(seeds: DataFrame, k: int, norm: bool = False) -> DataFrame:
    """One-hot rows as doubles; with ``norm`` each class's column sums to 1."""
    X = one_hot(seeds, k).select("node", *[F.col(c).cast("double").alias(c) for c in names(k)])
    if norm:
        sizes = seeds.groupBy("cls").agg(F.count(F.lit(1)).alias("n")).collect()  # one row a class
        of = {r.cls: r.n for r in sizes}
        X = X.select("node", *[(F.col(c) / F.lit(float(of.get(i, 1)))).alias(c) for i, c in enumerate(names(k))])
    return X


def harmonic(edges: DataFrame, seeds: DataFrame, k: int, r: int = 4) -> DataFrame:
    """Seeds stay; every other node takes the weighted mean of its neighbours."""
    return propagate(edges, seeds, np.eye(k), alpha=1.0, gamma=1.0, eps=1.0, r=r, centred=False, start=_plain(seeds, k))


def consistency(edges: DataFrame, seeds: DataFrame, k: int, a: float = 0.9, r: int = 4) -> DataFrame:
    """a S B + (1 - a) X with the symmetric scaling S."""
    return propagate(edges, seeds, np.eye(k), alpha=0.5, beta=0.5, eps=a, keep=1 - a, r=r, centred=False, start=_plain(seeds, k))


def neighborhood(edges: DataFrame, seeds: DataFrame, k: int, a: float = 0.9, r: int = 4) -> DataFrame:
    """a R B + (1 - a) X with the row scaling R (edge weights as given)."""
    return propagate(edges, seeds, np.eye(k), alpha=1.0, eps=a, keep=1 - a, r=r, centred=False, start=_plain(seeds, k))


def restart_walk(edges: DataFrame, seeds: DataFrame, k: int, a: float = 0.9, r: int = 4, seed_norm: bool = True) -> DataFrame:
    """A walk with restarts for each class: a C b + (1 - a) x with the column scaling C; with ``seed_norm`` each x sums to 1.

    The scaling changes the arg-max where classes have unequal numbers of seeds.
    """
    return propagate(edges, seeds, np.eye(k), beta=1.0, eps=a, keep=1 - a, r=r, centred=False, start=_plain(seeds, k, seed_norm))


def two_class(edges: DataFrame, seeds: DataFrame, h: float = 0.1, r: int = 10) -> DataFrame:
    """node, b0: the linear method for two classes with one number a node, b = x + c2 A b - c1 D b; b > 0 means class 0."""
    c1, c2 = 4 * h * h / (1 - 4 * h * h), 2 * h / (1 - 4 * h * h)
    P, deg = edges.repartition("dst").persist(), degrees(edges).persist()
    X = seeds.select("node", F.when(F.col("cls") == 0, F.lit(0.5)).otherwise(F.lit(-0.5)).alias("b0"))
    B = X
    for i in range(1, r + 1):
        B = summed([messages(P, B, 1, None, c2), X, scaled(B.join(deg, "node"), F.lit(-c1) * F.col("deg"), 1)], 1)
        B = cut(B) if i % CUT == 0 or i == r else B
    P.unpersist(), deg.unpersist()
    return B


def settle_steps(edges: DataFrame, seeds: DataFrame, K: np.ndarray, most: int = 10, *, alpha=0.0, beta=0.0, gamma=0.0, eps: float = 0.1) -> DataFrame:
    """r, changed: nodes whose class differs between r - 1 and r updates; the labelling has settled from where on it is 0.

    The classes after each update are rows of one frame, so the changes of all updates come from one window by node.
    """
    k = len(K)
    P = operator(edges, seeds, alpha, beta, gamma).repartition("dst").persist()
    X = residual(seeds, k)
    B, told = X, predict(X, k).select("node", "cls", F.lit(0).alias("r"))
    for r in range(1, most + 1):
        B = cut(step(P, X, B, center(K), eps, None))
        told = told.unionByName(predict(B, k).select("node", "cls", F.lit(r).alias("r")))
    P.unpersist()
    before = F.lag("cls").over(W.partitionBy("node").orderBy("r"))
    return told.withColumn("new", before.isNull() | (before != F.col("cls"))).filter("r > 0").groupBy("r").agg(F.sum(F.col("new").cast("long")).alias("changed"))


def vote_normalised(edges: DataFrame, seeds: DataFrame, k: int, r: int = 4) -> DataFrame:
    """Relational neighbour voting in its probabilistic form: neighbour averages, rows normalised to sum 1, seeds kept."""
    X = one_hot(seeds, k).select("node", *[F.col(c).cast("double").alias(c) for c in names(k)])
    B = X
    for _ in range(r):
        total = sum((F.col(c) for c in names(k)), F.lit(0.0))
        new = send(edges, B, k).join(seeds.select("node"), "node", "left_anti").select("node", *[(F.col(c) / total).alias(c) for c in names(k)])
        B = X.unionByName(new)
    return B


def pagerank(edges: DataFrame, *, a: float = 0.85, r: int = 4, echo: bool = False) -> DataFrame:
    """node, b0: random walk with jumps; with ``echo`` what a node gets back of its own weight is taken out.

    The scaling is a factor of the sending node, so edges stay as they are; the echo diagonal of the symmetric graph is a sum over
    neighbours that goes along with the first step's messages, in place of a join of edges to edges.
    """
    E = edges.select("src", "dst", "w").repartition("dst").persist()
    facts = cut(E.groupBy(F.col("src").alias("node")).agg((1 / F.sum("w")).alias("inv")))  # a row a node
    n = facts.count()
    jump = facts.select("node", F.lit((1 - a) / n).alias("b0"))
    f = facts.select("node", F.lit(1.0 / n).alias("b0"), "inv", F.lit(0.0).alias("q"))
    for i in range(r):
        measured = echo and i == 0
        sent = f.select(F.col("node").alias("dst"), (F.lit(a) * F.col("b0") * F.col("inv")).alias("b0"), "inv")
        got = [F.col("src").alias("node"), (F.col("w") * F.col("b0")).alias("b0"), *([(F.col("w") * F.col("w") * F.col("inv")).alias("q")] if measured else [])]
        rows = E.join(sent, "dst").select(*got).unionByName(jump, allowMissingColumns=True)
        new = rows.groupBy("node").agg(F.sum("b0").alias("new"), *([F.sum("q").alias("s")] if measured else []))
        q = F.col("s") * F.col("inv") if measured else F.col("q")
        less = F.lit(a * a) * q * F.col("b0") if echo else F.lit(0.0)
        f = cut(f.join(new, "node").select("node", (F.col("new") - less).alias("b0"), "inv", q.alias("q")))
    E.unpersist()
    return f.select("node", "b0")


def energy(edges: DataFrame, beliefs: DataFrame, seeds: DataFrame, K: np.ndarray, *, alpha=0.0, beta=0.0, gamma=0.0, eps=1.0, echo=False) -> DataFrame:
    """energy: squared distance between the beliefs and their own update; 0 at the fixed point."""
    k, K = len(K), center(K)
    P = operator(edges, seeds, alpha, beta, gamma)
    gap = add([(step(P, residual(seeds, k), beliefs, K, eps, echo_diagonal(P) if echo else None), 1.0), (beliefs, -1.0)], k)
    return gap.agg(F.sum(sum((F.col(c) * F.col(c) for c in names(k)), F.lit(0.0))).alias("energy"))


def smooth_energy(edges: DataFrame, beliefs: DataFrame, seeds: DataFrame, K: np.ndarray, mu: float = 1.0) -> DataFrame:
    """energy: distance from the seeds plus mu/2 times the weighted distances of beliefs from their modulated neighbours."""
    k = len(K)
    fit = add([(beliefs, 1.0), (residual(seeds, k), -1.0)], k).agg(F.sum(sum((F.col(c) * F.col(c) for c in names(k)), F.lit(0.0))).alias("f"))
    there = beliefs.select(F.col("node").alias("dst"), *[c.alias(f"m{d}") for d, c in enumerate(modulate(k, center(K)))])
    pairs = edges.join(beliefs.withColumnRenamed("node", "src"), "src").join(there, "dst")
    smooth = pairs.agg(F.sum(F.col("w") * sum((F.pow(F.col(f"b{c}") - F.col(f"m{c}"), 2) for c in range(k)), F.lit(0.0))).alias("s"))
    return fit.crossJoin(smooth).select((F.col("f") + F.lit(mu / 2) * F.coalesce("s", F.lit(0.0))).alias("energy"))  # one row each


def dot(a: list[str], b: list[str]):
    return sum((F.col(x) * F.col(y) for x, y in zip(a, b, strict=True)), F.lit(0.0))


def smoothness(edges: DataFrame, beliefs: DataFrame, K: np.ndarray, normalised: bool = False) -> DataFrame:
    """energy: f'R(Kf) for the graph Laplacian R = D - W, or I - D^-1/2 W D^-1/2 where ``normalised``; low where neighbours agree by K."""
    k = len(K)
    b, m = names(k), names(k, "m")
    there = beliefs.select("node", *[c.alias(f"m{d}") for d, c in enumerate(modulate(k, K))])
    own = beliefs.join(there, "node").join(degrees(edges), "node").agg(F.sum((F.lit(1.0) if normalised else F.col("deg")) * dot(b, m)).alias("own"))
    pairs = (scale_edges(edges, *SYM) if normalised else edges).join(beliefs.withColumnRenamed("node", "src"), "src").join(there.withColumnRenamed("node", "dst"), "dst")
    return own.crossJoin(pairs.agg(F.sum(F.col("w") * dot(b, m)).alias("across"))).select((F.coalesce("own", F.lit(0.0)) - F.coalesce("across", F.lit(0.0))).alias("energy"))  # one row each


def reconstruction_energy(edges: DataFrame, beliefs: DataFrame, k: int) -> DataFrame:
    """energy: squared distance of beliefs from the weighted mean of their neighbours' beliefs."""
    gap = add([(send(scale_edges(edges, *ROW), beliefs, k), -1.0), (beliefs, 1.0)], k)
    return gap.agg(F.sum(dot(names(k), names(k))).alias("energy"))


def closed_form(edges: DataFrame, seeds: DataFrame, K: np.ndarray, *, alpha=0.0, beta=0.0, gamma=0.0, eps=0.1, echo=False, most: int = 6_000) -> dict[int, np.ndarray]:
    """Dense solution of the fixed point on the driver, for tests: refused above ``most`` unknowns (nodes times classes)."""
    k, Kc = len(K), center(K)
    P = operator(edges, seeds, alpha, beta, gamma)
    n = P.select(F.explode(F.array("src", "dst")).alias("node")).unionByName(seeds.select("node")).agg(F.countDistinct("node")).first()[0]
    if n * k > most:
        raise ValueError(f"closed_form is for graphs of up to {most} unknowns, this one has {n * k}")
    rows, xs = P.collect(), residual(seeds, k).collect()  # (most / k)^2 entries at most
    nodes = sorted({r.src for r in rows} | {r.dst for r in rows} | {x.node for x in xs})
    at = {n: i for i, n in enumerate(nodes)}
    A, X = np.zeros((len(nodes), len(nodes))), np.zeros((len(nodes), k))
    for r in rows:
        A[at[r.src], at[r.dst]] += r.w
    for x in xs:
        X[at[x.node]] = x[1:]
    system = np.eye(len(nodes) * k) - eps * np.kron(A, Kc.T)
    if echo:
        system += eps**2 * np.kron(np.diag((A * A.T).sum(1)), (Kc @ Kc).T)
    B = np.linalg.solve(system, X.reshape(-1)).reshape(-1, k)
    return {n: B[i] for n, i in at.items()}


def belief_propagation(edges: DataFrame, seeds: DataFrame, K: np.ndarray, r: int = 4, prior: float = 0.9) -> DataFrame:
    """node, b0.. : loopy belief propagation in log space; a message leaves out what came back from its receiver."""
    k, K = len(K), np.clip(K, 1e-9, None)
    cols = names(k)
    nodes = edges.select(F.col("src").alias("node")).distinct().join(seeds, "node", "left")
    low = float(np.log((1 - prior) / max(1, k - 1)))
    log_prior = nodes.select("node", *[F.when(F.col("cls") == c, F.lit(float(np.log(prior)))).when(F.col("cls").isNotNull(), F.lit(low)).otherwise(F.lit(float(np.log(1 / k)))).alias(f"p{c}") for c in range(k)])
    m = edges.select("src", "dst", *[F.lit(0.0).alias(c) for c in cols])  # message of src to dst
    for i in range(r + 1):
        got = m.groupBy(F.col("dst").alias("node")).agg(*[F.sum(c).alias(c) for c in cols])
        full = log_prior.join(got, "node", "left").select("node", *[(F.coalesce(c, F.lit(0.0)) + F.col(f"p{j}")).alias(c) for j, c in enumerate(cols)])
        if i == r:
            top = F.greatest(*cols)
            e = full.select("node", *[F.exp(F.col(c) - top).alias(c) for c in cols])
            return e.select("node", *[(F.col(c) / sum((F.col(x) for x in cols), F.lit(0.0))).alias(c) for c in cols])
        back = m.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *[F.col(c).alias(f"r{j}") for j, c in enumerate(cols)])
        base = edges.select("src", "dst").join(full.withColumnRenamed("node", "src"), "src").join(back, ["src", "dst"])
        base = base.select("src", "dst", *[(F.col(c) - F.col(f"r{j}")).alias(c) for j, c in enumerate(cols)]).withColumn("top", F.greatest(*cols))
        sent = base.select("src", "dst", *[F.log(sum((F.exp(F.col(f"b{c}") - F.col("top")) * F.lit(float(K[c, d])) for c in range(k)), F.lit(0.0))).alias(f"b{d}") for d in range(k)])
        m = sent.withColumn("top", F.greatest(*cols)).select("src", "dst", *[(F.col(c) - F.col("top")).alias(c) for c in cols])
        m = cut(m)
