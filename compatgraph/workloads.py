"""The experiments on planted graphs: each returns one row a setting.

Graphs are planted over the keys of ``customer`` unless a workload says otherwise, and settings are the published ones but for the number of
nodes, which is the table's.  Sweeps share passes: all pairs of step count and stability ratio come from one run of the steps, and all
repetitions or label shares of a graph from one run of the hops (as classes of their own).  What a workload caches it releases.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

import numpy as np
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.compat import balanced_rows, center, cyclic_compat, fit_powers, identity_compat, nearest_compat, normalize_counts, radius, strength_compat
from .operators.labels import accuracy, hide_labels, hold_out, modulate, names, predict, residual, uniform
from .plans.blocks import Blocks
from .plans.estimate import estimate_energy
from .plans.lineage import cut, shared_dir
from .plans.planted import clustered_adjacency, degree_histogram, planted_graph, ranked
from .plans.propagate import members, operator, propagate, propagate_many, send, spectral_radii, spectral_radius
from .plans.walks import batched_matrices, count_matrices, path_matrix
from .sources.tables import doc_labels, knn, page_labels, pages, same_text, shared_lines, step_labels, steps, table, trade, trade_labels, tree, tree_labels, turn_labels, turns

REC = {"alpha": 0.0, "beta": 1.0, "gamma": 0.5, "r": 4}
SHARES = (0.001, 0.01, 0.02, 0.1, 0.5, 0.9)
OPTIONS = ((1, 1, 10.0), (2, 1, 10.0), (3, 1, 10.0), (4, 1, 10.0), (5, 1, 10.0), (1, 2, 10.0), (2, 2, 10.0), (3, 2, 10.0), (4, 2, 10.0), (5, 2, 10.0), (1, 3, 10.0), (2, 3, 10.0), (3, 3, 10.0), (4, 3, 10.0), (5, 3, 10.0), (5, 1, 0.1), (5, 1, 1.0), (5, 1, 100.0), (5, 1, 1000.0))


def hide_stratified(labels: DataFrame, f: float, run: int | None = None) -> DataFrame:
    """Seeds: of each class the share ``f`` of least hash, one at least.  Equal shares matter for s > 1, where the mean of the seeds grows fastest."""
    sizes = labels.groupBy("cls").agg(F.greatest(F.lit(1), F.round(F.count(F.lit(1)) * f)).alias("most"))
    key = F.col("node") if run is None else F.concat_ws(":", F.lit(str(run)), F.col("node").cast("string"))
    own = ranked(labels.withColumn("u", uniform(key)), ["cls"], "u", ["node"], "r").join(F.broadcast(sizes), "cls")  # one row a class
    return own.filter("r <= most").select("node", "cls")


#: Graphs of a grid that are worked on at a time.
SIDE_BY_SIDE = 2
#: Folders of graphs planted in this application, by table and parameters: the workloads of one application plant each graph once.
_PLANTED: dict[tuple, str] = {}


def _graph(spark: SparkSession, d: str, h: float, degree: float, name: str, key: str) -> tuple[DataFrame, DataFrame]:
    at = (spark.sparkContext.applicationId, str(d), h, degree, name)
    if at in _PLANTED:
        try:
            return spark.read.parquet(f"{_PLANTED[at]}/edges"), spark.read.parquet(f"{_PLANTED[at]}/labels")
        except AnalysisException:  # the folder was cleared
            del _PLANTED[at]
    edges, labels, _ = planted_graph(table(spark, d, name, key).withColumnRenamed(key, "node"), strength_compat(h), degree)
    path = f"{shared_dir(spark)}/planted-{uuid.uuid4().hex}"
    edges.write.parquet(f"{path}/edges"), labels.write.parquet(f"{path}/labels")
    _PLANTED[at] = path
    return _graph(spark, d, h, degree, name, key)


@contextmanager
def planted(spark: SparkSession, d: str, h: float, degree: float, f: float = 0.1, name: str = "customer", key: str = "c_custkey", nodes: DataFrame | None = None) -> Iterator[tuple[DataFrame, DataFrame, DataFrame]]:
    """Edges (cached by sending node and in its order while in use, so that no step sorts them), labels and seeds of a planted graph."""
    edges, labels = _graph(spark, d, h, degree, name, key) if nodes is None else planted_graph(nodes, strength_compat(h), degree)[:2]
    edges = edges.repartition("dst").sortWithinPartitions("dst").persist()
    try:
        yield edges, labels, cut(hide_stratified(labels, f))
    finally:
        edges.unpersist()


def score(edges, labels, seeds, K, **options) -> float:
    got = accuracy(hold_out(predict(propagate(edges, seeds, K, **options), len(K)), labels, seeds)).first()
    return (got.correct or 0) / max(1, got.hidden)


def score_many(edges, labels, sets, runs, k: int, held: Blocks | None = None) -> list[float]:
    """``score`` of each run of ``propagate_many``: all runs share the passes over the edges, and one aggregation measures them."""
    held = labels.join(propagate_many(edges, sets, runs, k, held), "node", "left")
    counts = []
    for j, x in enumerate(runs):
        b = [F.round(f"b{j}_{c}", 9) for c in range(k)]
        said = F.coalesce(*[F.when(v == F.greatest(*b), F.lit(c)) for c, v in enumerate(b)])
        hidden = F.col(f"s{x['seeds']}").isNull()
        counts += [F.count(F.when(hidden, F.lit(1))).alias(f"h{j}"), F.count(F.when(hidden & (said == F.col("cls")), F.lit(1))).alias(f"c{j}")]
    got = held.agg(*counts).first()
    return [got[f"c{j}"] / max(1, got[f"h{j}"]) for j in range(len(runs))]


def rows(spark: SparkSession, found: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(found, schema)


def headline(spark, d, name: str = "customer", key: str = "c_custkey") -> DataFrame:
    """Known K with the recommended member, the linear baseline, estimated K, identity, random guess; few labels."""
    h = 8
    K = strength_compat(h)
    with planted(spark, d, h, 25, 0.008, name, key) as (edges, labels, seeds):
        est = fit_powers([normalize_counts(M) for M in count_matrices(edges, seeds, 3, 5)])[0]
        found = [("recommended", K, {"s": 5.0, **REC}), ("linear", K, {"s": 0.5, "r": 10}), ("estimated", est, {"s": 5.0, **REC}), ("estimated, linear", est, {"s": 0.5, "r": 10}), ("identity", identity_compat(3), {"s": 0.5, **REC})]
        scored = [(who, score(edges, labels, seeds, M, **o)) for who, M, o in found]
    return rows(spark, [*scored, ("random", 1 / 3)], "method string, accuracy double")


def step_terms(P: DataFrame, seeds: DataFrame, K: np.ndarray, most: int) -> DataFrame:
    """node, i, b0..: P^i X K^i for i = 0 .. ``most``.  Beliefs for any eps and r are their sums with eps^i over i <= r."""
    k, Z = len(K), residual(seeds, len(K))
    out = Z.withColumn("i", F.lit(0))
    for i in range(1, most + 1):
        Z = cut(send(P, Z.select("node", *modulate(k, center(K))), k))
        out = out.unionByName(Z.withColumn("i", F.lit(i)))
    return out


def sweep_steps(spark, d, steps_=(1, 2, 4, 10, 20), ratios=(0.1, 0.5, 1.0, 3.0, 10.0)) -> DataFrame:
    """Iterations by stability ratio on the raw matrix: the terms of 20 steps give all settings, as columns of one aggregation."""
    K = strength_compat(5)
    with planted(spark, d, 5, 25, 0.05) as (edges, labels, seeds):
        limit = 1 / (spectral_radius(edges) * radius(center(K)))
        settings = [(r, s) for r in steps_ for s in ratios]
        # shares of the limit: the terms stay in range when scaled with it
        terms = step_terms(edges.select("src", "dst", (F.col("w") * limit).alias("w")), seeds, K, max(steps_))
        sums = [F.sum(F.when(F.col("i") <= r, F.col(c) * F.pow(F.lit(s), "i"))).alias(f"s{j}_{c}") for j, (r, s) in enumerate(settings) for c in names(3)]
        wide = terms.groupBy("node").agg(*sums).join(seeds.select("node"), "node", "left_anti").join(labels.withColumnRenamed("cls", "truth"), "node", "right")
        hidden = wide.join(seeds.select("node"), "node", "left_anti")
        right = []
        for j in range(len(settings)):
            b = [F.round(F.col(f"s{j}_{c}"), 9) for c in names(3)]
            cls = F.coalesce(*[F.when(x == F.greatest(*b), F.lit(c)) for c, x in enumerate(b)])
            right.append(F.avg(F.coalesce((cls == F.col("truth")).cast("int"), F.lit(0))).alias(f"a{j}"))
        got = hidden.agg(*right).first()
    return rows(spark, [(r, s, float(got[j] or 0)) for j, (r, s) in enumerate(settings)], "r int, s double, accuracy double")


def scaling_grid(spark, d) -> DataFrame:
    """Scaling and clamping, echo on and off."""
    K, own = strength_compat(5), radius(center(strength_compat(5)))
    settings = [(0, 0, 0, False), (0, 0, 1, False), (0, 1, 0, False), (0.5, 0.5, 0, False), (0.5, 0.5, 1, False), (0, 1, 0.5, False), (0, 1, 0.5, True)]
    with planted(spark, d, 5, 25, 0.05) as (edges, labels, seeds):
        raw = dict(zip((0, 1), spectral_radii(edges, seeds, [0.0, 1.0]), strict=True))
        # scaled operators have radius 1, clamped or not, with and without echo at one eps; raw ones have their own
        runs = [{"seeds": 0, "K": K, "alpha": a, "beta": b, "gamma": g, "echo": echo, "r": 4, "eps": 3.0 / own / (1.0 if a + b == 1 else raw[g])} for a, b, g, echo in settings]
        found = [(float(a), float(b), float(g), echo, x) for (a, b, g, echo), x in zip(settings, score_many(edges, labels, [seeds], runs, 3), strict=True)]
    return rows(spark, found, "alpha double, beta double, gamma double, echo boolean, accuracy double")


def ratio_clamped(spark, d) -> DataFrame:
    """Unscaled stability ratio (radius at eps = 1) with and without clamping."""
    k = radius(center(strength_compat(5)))
    with planted(spark, d, 5, 25, 0.05) as (edges, _, seeds):
        found = [(g, k * spectral_radius(operator(edges, seeds, 0, 0, g))) for g in (0.0, 1.0)]
    return rows(spark, found, "gamma double, s0 double")


def estimator_error(spark, d) -> DataFrame:
    """Distance from the planted K by hops, normalisation and weight; paths with and without backtracking."""
    h, found = 8, []
    with planted(spark, d, h, 25, 0.1) as (edges, _, seeds):
        for back in (False, True):
            M = count_matrices(edges, seeds, 3, 5, back)
            for lmax, variant, lam in OPTIONS:
                K = fit_powers([normalize_counts(m, variant) for m in M[:lmax]], lam)[0]
                found.append((back, lmax, variant, lam, float(np.linalg.norm(K - strength_compat(h)))))
    return rows(spark, found, "backtracking boolean, lmax int, variant int, lambda double, l2 double")


def degree_and_labels(spark, d, degrees=(5, 10, 25), shares=SHARES) -> DataFrame:
    """Error of one-hop and five-hop estimates by mean degree and share of labels; all shares of a graph in one run of the hops."""
    found = []
    for degree in degrees:
        with planted(spark, d, 8, degree) as (edges, labels, _):
            for f, M in zip(shares, batched_matrices(edges, [cut(hide_stratified(labels, f)) for f in shares], 3, 5), strict=True):
                T = [normalize_counts(m) for m in M]
                found += [(degree, f, lmax, float(np.linalg.norm(fit_powers(T[:lmax])[0] - strength_compat(8)))) for lmax in (1, 5)]
    return rows(spark, found, "degree int, f double, lmax int, l2 double")


def bias(spark, d, runs: int = 10, name: str = "customer", key: str = "c_custkey") -> DataFrame:
    """Mean top entry of the normalised counts by hop, with and without backtracking, over repetitions, against K^l."""
    found = []
    with planted(spark, d, 8, 10, 0.1, name, key) as (edges, labels, _):
        sets = [cut(hide_labels(labels, 0.1, run)) for run in range(runs)]
        for back in (False, True):
            T = [[normalize_counts(m) for m in M] for M in batched_matrices(edges, sets, 3, 4, back)]
            for l in range(4):
                top = [float(np.mean([t[l][c, p] for c, p in enumerate((1, 0, 2) if l % 2 == 0 else (0, 1, 2))])) for t in T]
                want = float(np.linalg.matrix_power(strength_compat(8), l + 1)[(0, 1) if l % 2 == 0 else (0, 0)])
                found.append((back, l + 1, float(np.mean(top)), float(np.std(top, ddof=1) / len(top) ** 0.5) if runs > 1 else float("nan"), want))
    return rows(spark, found, "backtracking boolean, hop int, measured double, error double, expected double")


def three_estimators(spark, d, h: int = 8, s: float = 5.0) -> DataFrame:
    """Estimate, then label, with each estimator; known K with the baseline for comparison."""
    found = []
    with planted(spark, d, h, 25, 0.05) as (edges, labels, seeds):
        M = [normalize_counts(m) for m in count_matrices(edges, seeds, 3, 5)]
        for name, K in (("multihop", fit_powers(M)[0]), ("onehop", nearest_compat(M[0])), ("energy", estimate_energy(edges, seeds, 3, alpha=1.0)), ("energy, labelled rows", estimate_energy(edges, seeds, 3, alpha=1.0, rows="labelled")), ("known", strength_compat(h))):
            found.append((h, name, float(np.linalg.norm(K - strength_compat(h))), score(edges, labels, seeds, K, s=s, **REC)))
        found.append((h, "known, linear", 0.0, score(edges, labels, seeds, strength_compat(h), s=0.5, r=10)))
    return rows(spark, found, "h int, estimator string, l2 double, accuracy double")


def path_growth(spark, d) -> DataFrame:
    """Entries of the explicit path matrices (up to 3 hops) against the n x k state of the chained counts (up to 8), with seconds."""
    found = []
    with planted(spark, d, 8, 10, 0.1) as (edges, labels, seeds):
        n = labels.count()
        for l in range(1, 9):
            t = time.perf_counter()
            entries = path_matrix(edges, l).count() if l <= 3 else None
            explicit, t = (time.perf_counter() - t if l <= 3 else None), time.perf_counter()
            count_matrices(edges, seeds, 3, l)
            found.append((l, entries, 3 * n, explicit, time.perf_counter() - t))
    return rows(spark, found, "hop int, entries long, state long, explicit_sec double, chained_sec double")


def phases(spark, d, name: str = "orders", key: str = "o_orderkey", degree: float = 25, nodes: DataFrame | None = None) -> DataFrame:
    """Seconds of each phase on one graph, with edges cached by sending node and placed in blocks, as an engine that labels a graph holds them."""
    found = []
    with planted(spark, d, 8, degree, 0.01, name, key, nodes) as (edges, labels, seeds):
        m, K = edges.count(), strength_compat(8)
        seeds = seeds.persist()
        seeds.count()
        held = Blocks(edges, labels)
        held.rdd.count()

        def timed(phase, action):
            t = time.perf_counter()
            action()
            found.append((phase, m // 2, time.perf_counter() - t))

        timed("one-hop", lambda: count_matrices(edges, seeds, 3, 1))
        timed("energy fit", lambda: estimate_energy(edges, seeds, 3, alpha=1.0))
        timed("multi-hop", lambda: fit_powers([normalize_counts(x) for x in count_matrices(edges, seeds, 3, 5, held=held)]))
        timed("stability limit", lambda: spectral_radius(edges, held=held))
        timed("propagation 10", lambda: propagate(edges, seeds, K, beta=1.0, gamma=0.5, s=3.0, r=10, held=held).agg(F.sum("b0")).first())
        seeds.unpersist(), held.drop()
    return rows(spark, found, "phase string, edges long, seconds double")


def scalability(spark, d, sizes=(("customer", "c_custkey"), ("part", "p_partkey"), ("orders", "o_orderkey"))) -> DataFrame:
    """The phases over growing graphs: the keys of three tables.  They are planted side by side; only then the phases run, one at a time."""
    with ThreadPoolExecutor(len(sizes)) as pool:
        list(pool.map(lambda of: _graph(spark, d, 8, 25, *of), sizes))
    out = None
    for name, key in sizes:
        own = phases(spark, d, name, key).withColumn("keys", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


def weak_potential(spark, d) -> DataFrame:
    """Weak attraction (h = 2) with few and with most labels: the choice of scaling matters less once labels are dense."""
    found = []
    for f in (0.05, 0.9):
        with planted(spark, d, 2, 25, f) as (edges, labels, seeds):
            for name, options in (("linear", {"s": 0.5, "r": 10}), ("symmetric, clamped", {"alpha": 0.5, "beta": 0.5, "gamma": 1.0, "s": 3.0, "r": 4}), ("recommended", {"s": 3.0, **REC})):
                found.append((f, name, score(edges, labels, seeds, strength_compat(2), **options)))
    return rows(spark, found, "f double, method string, accuracy double")


def real_labels(spark, d) -> DataFrame:
    """Estimate, then label, on graphs of the given tables; roles of turns carry a signal, the others are held against the majority share."""
    vectors = table(spark, d, "embeddings", "vec_id", "label").select(F.col("vec_id").alias("node"), F.col("label").cast("int").alias("cls"))
    graphs = (
        ("turns", turns(spark, d), turn_labels(spark, d), 3), ("trade", trade(spark, d), trade_labels(spark, d), 5), ("steps", steps(spark, d), step_labels(spark, d), 5), ("vectors", knn(spark, d), vectors, 10),
        ("quality of equal texts", same_text(spark, d), doc_labels(spark, d, "quality"), 2), ("toxic, shared lines", shared_lines(spark, d), doc_labels(spark, d, "toxic"), 2), ("language of pages", pages(spark, d), page_labels(spark, d), 4),
    )
    found = []
    for name, edges, labels, k in graphs:
        # scored on the nodes that have an edge; the majority share is theirs
        edges = edges.repartition("dst").persist()
        labels = cut(labels.join(edges.select(F.col("src").alias("node")).distinct(), "node", "left_semi"))
        seeds = cut(hide_labels(labels, 0.5))
        K = nearest_compat(normalize_counts(count_matrices(edges, seeds, k, 1)[0]))
        got = accuracy(hold_out(predict(propagate(edges, seeds, K, s=0.5, **REC), k), labels, seeds)).first()
        sizes = [r["count"] for r in labels.join(seeds.select("node"), "node", "left_anti").groupBy("cls").count().collect()]  # one row a class
        found.append((name, got.hidden, (got.correct or 0) / max(1, got.hidden), (got.unreached or 0) / max(1, got.hidden), max(sizes, default=0) / max(1, sum(sizes))))
        edges.unpersist()
    return rows(spark, found, "graph string, hidden long, accuracy double, unreached double, majority double")


def echo_on_tree(spark, d) -> DataFrame:
    """The echo term on a forest, where every path back is an echo."""
    edges, labels = tree(spark, d), tree_labels(spark, d)
    seeds, K = cut(hide_labels(labels, 0.1)), 0.1 * np.ones((5, 5)) + 0.5 * np.eye(5)
    found = []
    for echo in (False, True):
        got = accuracy(hold_out(predict(propagate(edges, seeds, K, eps=0.5 / radius(center(K)), r=4, beta=1.0, echo=echo), 5), labels, seeds)).first()
        found.append((echo, (got.correct or 0) / max(1, got.hidden)))
    return rows(spark, found, "echo boolean, accuracy double")


def generator_tables(spark, d) -> DataFrame:
    """Class-pair counts and degrees of the generator's directed examples: uneven classes, and rows weighted for even mean degrees."""
    keys, out = table(spark, d, "customer", "c_custkey").select(F.col("c_custkey").alias("node")), None
    alpha = [1 / 6, 1 / 3, 1 / 2]
    for name, K in (("uneven degrees", cyclic_compat(8)), ("even degrees", balanced_rows(cyclic_compat(8), alpha))):
        arcs, labels, _ = planted_graph(keys, K, 9, alpha=alpha, delta=0.4, directed=True, independent=True)
        a, b = labels.toDF("src", "c"), labels.toDF("dst", "d")
        pairs = arcs.join(a, "src").join(b, "dst").groupBy("c", "d").agg(F.count(F.lit(1)).alias("n")).select(F.lit("pairs").alias("kind"), F.col("c").alias("x"), F.col("d").cast("long").alias("y"), "n")
        degrees = degree_histogram(arcs, labels).select(F.lit("degrees").alias("kind"), F.col("cls").alias("x"), F.col("deg").alias("y"), "n")
        bins = clustered_adjacency(arcs, labels, 100).select(F.lit("clusters").alias("kind"), F.col("row_bin").alias("x"), F.col("col_bin").cast("long").alias("y"), "n")
        own = pairs.unionByName(degrees).unionByName(bins).withColumn("graph", F.lit(name))
        out = own if out is None else out.unionByName(own)
    return out


def grid(spark, d, strengths=(3, 8), degrees=(10,), shares=(0.05,), runs: int = 2) -> DataFrame:
    """The grid of parameters, one record a run: strength, degree, label share and draw, by how K is had and which member labels.

    All runs on a graph go side by side, and so do the counts of its draws and the graphs; a record's seconds are its equal share of its
    graph's labelling.
    """
    ways = {"linear": ("linear", {"s": 0.5, "r": 10}), "recommended": ("recommended", {"r": 4})}
    draws = [(f, run) for f in shares for run in range(runs)]

    def on_graph(of: tuple) -> list[tuple]:
        h, degree = of
        with planted(spark, d, h, degree) as (edges, labels, _), ThreadPoolExecutor(2) as pool:
            held = Blocks(edges, labels)
            root = pool.submit(spectral_radius, edges, held=held)
            sets = [cut(hide_stratified(labels, f, run)) for f, run in draws]
            counts = batched_matrices(edges, sets, 3, 5, held=held)
            rho = root.result()
            todo, records = [], []
            for i, ((f, run), M) in enumerate(zip(draws, counts, strict=True)):
                T = [normalize_counts(m) for m in M]
                for had, K in (("known", strength_compat(h)), ("multihop", fit_powers(T)[0]), ("onehop", nearest_compat(T[0])), ("identity", identity_compat(3))):
                    for who, (name, options) in ways.items():
                        own = options | ({"s": float(h if h <= 3 else 5)} if who == "recommended" else {})
                        kind = dict(members()[name])
                        M_ = np.eye(3) if kind.pop("identity", False) else K
                        limit = (1.0 if kind["alpha"] + kind["beta"] == 1 else rho) * radius(center(M_))
                        todo.append({"seeds": i, "K": M_, **kind, "r": own["r"], "eps": own["s"] * (min(1 / limit, 1e6) if limit > 1e-12 else 1e6)})
                        records.append(({"strength": str(h), "degree": str(degree), "share": str(f), "draw": str(run), "compat": had, "member": who, **{k: str(v) for k, v in members()[name].items()}, **{k: str(v) for k, v in own.items()}}, float(np.linalg.norm(K - strength_compat(h)))))
            t = time.perf_counter()
            scored = score_many(edges, labels, sets, todo, 3, held)
            each = (time.perf_counter() - t) / len(todo)
            held.drop()
        return [(uuid.uuid4().hex, params, x, l2, each) for (params, l2), x in zip(records, scored, strict=True)]

    graphs = [(h, degree) for h in strengths for degree in degrees]
    with ThreadPoolExecutor(min(len(graphs), SIDE_BY_SIDE)) as pool:
        found = [x for own in pool.map(on_graph, graphs) for x in own]
    return rows(spark, found, "run_id string, params map<string,string>, accuracy double, l2 double, seconds double")


def grid_stats(runs: DataFrame) -> DataFrame:
    """Mean, deviation and standard error of accuracy over the draws of each setting of ``grid``."""
    by = [F.col("params")[x].alias(x) for x in ("strength", "degree", "share", "compat", "member")]
    flat = runs.select(*by, "accuracy")
    return flat.groupBy("strength", "degree", "share", "compat", "member").agg(F.avg("accuracy").alias("mean"), F.stddev_samp("accuracy").alias("std"), (F.stddev_samp("accuracy") / F.sqrt(F.count(F.lit(1)))).alias("error"), F.count(F.lit(1)).alias("runs"))


WORKLOADS = {
    "w_headline": headline, "w_sweep_steps": sweep_steps, "w_scaling_grid": scaling_grid, "w_ratio_clamped": ratio_clamped, "w_estimator_error": estimator_error, "w_degree_and_labels": degree_and_labels, "w_bias": bias,
    "w_three_estimators": three_estimators, "w_three_estimators_weak": lambda spark, d: three_estimators(spark, d, 3, 3.0), "w_path_growth": path_growth, "w_scalability": scalability, "w_weak_potential": weak_potential,
    "w_real_labels": real_labels, "w_echo_on_tree": echo_on_tree, "w_generator_tables": generator_tables, "w_grid": lambda spark, d: grid_stats(grid(spark, d)),
}
