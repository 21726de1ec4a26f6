import itertools
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from compatgraph.functions import compat as C
from compatgraph.functions.compat import center, radius, strength_compat
from compatgraph.operators import labels as L
from compatgraph.operators import scaling as S
from compatgraph.plans import planted, propagate, walks
from compatgraph.sources.tables import normalise_edges

K = strength_compat(8)
RING = [(0, 1), (1, 2), (2, 3), (3, 0), (3, 4), (4, 5)]
CLASSES = [0, 1, 0, 1, 2, 0]


@pytest.fixture(scope="module")
def micro(spark):
    edges = normalise_edges(spark.createDataFrame([(a, b, 1.0) for a, b in RING], "a long, b long, w double")).cache()
    return edges, spark.createDataFrame(list(enumerate(CLASSES)), "node long, cls int").cache()


def counts(edges, seeds, l, back=False):
    return walks.count_matrices(edges, seeds, 3, l, back)[-1].astype(int).tolist()


def test_worked_counts(micro):
    edges, labels = micro
    assert counts(edges, labels, 1) == [[0, 4, 1], [4, 0, 1], [1, 1, 0]]
    assert counts(edges, labels, 2) == [[4, 1, 2], [1, 4, 0], [2, 0, 0]]
    assert counts(edges, labels, 3) == [[4, 4, 0], [4, 0, 2], [0, 2, 0]]
    assert counts(edges, labels, 4) == [[4, 2, 2], [2, 4, 0], [2, 0, 0]]


def test_chain_equals_walks_and_matrices(micro):
    edges, labels = micro
    for l in (2, 3):
        nb = {(r.src, r.dst): r.n for r in walks.nb_path_matrix(edges, l).collect()}
        assert nb == {(r.src, r.dst): r.n for r in walks.enumerate_walks(edges, l).collect()}
        full = {(r.src, r.dst): r.n for r in walks.path_matrix(edges, l).collect()}
        assert sum(full.values()) == sum(map(sum, counts(edges, labels, l, True)))
        assert sum(nb.values()) == sum(map(sum, counts(edges, labels, l)))
    with pytest.raises(ValueError):
        walks.path_matrix(edges, 4)


def test_echo_in_all_paths(spark):
    chain = normalise_edges(spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0)], "a long, b long, w double"))
    seeds = spark.createDataFrame([(0, 0), (1, 1), (2, 2)], "node long, cls int")
    assert counts(chain, seeds, 2, True) == [[1, 0, 1], [0, 2, 0], [1, 0, 1]]
    assert counts(chain, seeds, 2) == [[0, 0, 1], [0, 0, 0], [1, 0, 0]]


@pytest.mark.parametrize(("scaling", "gamma", "echo"), [(S.RAW, 0.0, False), (S.RAW, 0.0, True), (S.COL, 0.5, False), (S.SYM, 1.0, False), (S.ROW, 0.5, True)])
def test_iteration_reaches_the_closed_form(micro, scaling, gamma, echo):
    edges, labels = micro
    seeds, (a, b) = labels.filter("node in (0, 3, 4)"), scaling
    setting = {"alpha": a, "beta": b, "gamma": gamma, "eps": 0.25, "echo": echo}
    got = {r.node: np.array(r[1:]) for r in propagate.propagate(edges, seeds, K, r=25, **setting).collect()}
    want = propagate.closed_form(edges, seeds, K, **setting)
    assert all(np.allclose(got[n], want[n], atol=1e-5) for n in want)
    assert all(abs(v.sum()) < 1e-9 for v in got.values())  # residual rows stay residual
    if gamma == 1:
        assert all(np.allclose(got[n], np.eye(3)[CLASSES[n]] - 1 / 3) for n in (0, 3, 4))


def test_stability_limit(micro):
    edges, labels = micro
    A = np.zeros((6, 6))
    for a, b in RING:
        A[a, b] = A[b, a] = 1
    rho = radius(A)
    assert abs(propagate.spectral_radius(edges, 40, 1e-7) - rho) < 1e-3
    assert abs(propagate.stability_limit(edges, labels, K) - 1 / (rho * radius(center(K)))) < 1e-2
    assert propagate.stability_limit(edges, labels, K, beta=1.0) == pytest.approx(1 / 0.7)


def test_echo_diagonal_of_plain_graph_is_degree(micro):
    edges, _ = micro
    assert {r.node: r.q for r in S.echo_diagonal(edges).collect()} == {r.node: r.deg for r in S.degrees(edges).collect()}


def test_belief_propagation_is_exact_on_a_tree(spark):
    pairs = [(0, 1), (1, 2), (1, 3), (3, 4)]
    edges = normalise_edges(spark.createDataFrame([(a, b, 1.0) for a, b in pairs], "a long, b long, w double"))
    seeds = spark.createDataFrame([(0, 0), (4, 2)], "node long, cls int")
    got = {r.node: np.array([r.b0, r.b1, r.b2]) for r in propagate.belief_propagation(edges, seeds, K, r=6).collect()}
    prior = np.full((5, 3), 1 / 3)
    prior[0], prior[4] = [0.9, 0.05, 0.05], [0.05, 0.05, 0.9]
    want = np.zeros((5, 3))
    for x in itertools.product(range(3), repeat=5):
        p = np.prod([prior[i, c] for i, c in enumerate(x)]) * np.prod([K[x[a], x[b]] for a, b in pairs])
        for i, c in enumerate(x):
            want[i, c] += p
    want /= want.sum(1, keepdims=True)
    assert all(np.allclose(got[i], want[i], atol=1e-9) for i in range(5))


def test_empty_and_unseen(spark, micro):
    edges, labels = micro
    none = labels.filter("node < 0")
    assert propagate.propagate(edges, none, K, eps=0.1).count() == 0
    assert counts(edges, none, 2) == [[0] * 3] * 3
    assert propagate.propagate(edges.filter("w < 0"), labels, K, eps=0.1).count() == 6


def test_prediction_ties(spark):
    b = spark.createDataFrame([(1, 0.2, 0.2, 0.1), (2, 0.0, 0.1, 0.3)], "node long, b0 double, b1 double, b2 double")
    assert [tuple(r) for r in L.predict(b, 3).orderBy("node").collect()] == [(1, 0, True), (2, 2, False)]


def test_worked_degrees_and_classes(spark):
    nodes = spark.createDataFrame([(i, 0) for i in range(3)], "node long, cls int")
    assert sorted(r.d for r in planted.assign_degrees(nodes, [11], 1.0).collect()) == [2, 3, 6]
    got = planted.assign_classes(spark.range(6).withColumnRenamed("id", "node"), [2 / 6, 3 / 6, 1 / 6])
    assert sorted(r.cls for r in got.collect()) == [0, 0, 1, 1, 1, 2]


def test_planted_graph_is_exact(spark):
    edges, labels, M = planted.planted_graph(spark.range(300).withColumnRenamed("id", "node"), K, 8)
    got = np.zeros((3, 3), int)
    for r in planted.planted_check(edges, labels).collect():
        got[r.c, r.d] = r.n
    assert (got == M + M.T).all()
    assert edges.filter("src = dst").count() == 0 and edges.distinct().count() == edges.count() == 2400


def test_dense_blocks_raise_and_never_drop_arcs(spark):
    with pytest.raises(ValueError, match="arcs are still"):
        planted.planted_graph(spark.range(60).withColumnRenamed("id", "node"), K, 30, rounds=2)


def test_directed_examples(spark):
    """Uneven classes with a cyclic K, and its rows weighted so that mean out-degrees are even: exact budgets, no loops, no double arcs."""
    keys, alpha = spark.range(120).withColumnRenamed("id", "node"), [1 / 6, 1 / 3, 1 / 2]
    uneven, even = C.cyclic_compat(8), C.balanced_rows(C.cyclic_compat(8), alpha)
    assert (C.edge_budget(1080, uneven) == 36 * np.array([[1, 8, 1], [1, 1, 8], [8, 1, 1]])).all()
    M = C.edge_budget(1080, even)
    assert (M == 18 * np.array([[1, 8, 1], [2, 2, 16], [24, 3, 3]])).all() and (M.sum(1) / [20, 40, 60] == 9).all()
    symmetric = C.edge_budget(1080, K)
    assert (symmetric == 36 * np.array([[1, 8, 1], [8, 1, 1], [1, 1, 8]])).all()
    arcs, labels, budget = planted.planted_graph(keys, uneven, 4, alpha=alpha, delta=0.4, directed=True, independent=True)
    got = np.zeros((3, 3), int)
    for r in planted.planted_check(arcs, labels).collect():
        got[r.c, r.d] = r.n
    assert (got == budget).all() and arcs.count() == 480
    assert arcs.select(F.least("src", "dst"), F.greatest("src", "dst")).distinct().count() == 480 and arcs.filter("src = dst").count() == 0


def test_correlated_and_independent_degrees(spark):
    keys = spark.range(1_500).withColumnRenamed("id", "node")
    found = {}
    for independent in (False, True):
        arcs, _, _ = planted.planted_graph(keys, K, 6, directed=True, independent=independent)
        out, into = arcs.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("o")), arcs.groupBy(F.col("dst").alias("node")).agg(F.count("*").alias("i"))
        found[independent] = keys.join(out, "node", "left").join(into, "node", "left").fillna(0).agg(F.corr("o", "i")).first()[0]
    assert found[False] > 0.95 and abs(found[True]) < 0.3


def test_equal_degrees_are_ranked_in_parts(spark):
    """With equal degrees all fractions tie; their bucket is cut by rank, and the total is exact."""
    nodes = spark.range(30_000).select(F.col("id").alias("node"), F.lit(0).alias("cls"))
    got = planted.assign_degrees(nodes, [70_001], 0.0)
    assert sorted(r.d for r in got.groupBy("d").agg(F.count("*").alias("n")).collect()) == [2, 3] and got.agg(F.sum("d")).first()[0] == 70_001
    tied = nodes.withColumn("u", F.lit(7).cast("long")).withColumn("r", F.col("node") + 1)
    out = planted.ranked(tied, ["cls"], "u", ["r"], "q", "r")
    assert out.filter("q <> r").count() == 0
    plan = out._jdf.queryExecution().toString()
    assert "_p" in plan


def test_colouring_gadget(spark):
    """A proper colouring fits K = (J - I) / (k - 1) exactly, another labelling does not."""
    ring = normalise_edges(spark.createDataFrame([(i, (i + 1) % 6, 1.0) for i in range(6)], "a long, b long, w double"))
    for classes, conflicts in (([0, 1, 2, 0, 1, 2], 0), ([0, 0, 1, 2, 1, 2], 1)):
        labels = spark.createDataFrame(list(enumerate(classes)), "node long, cls int")
        T = C.normalize_counts(walks.count_matrices(ring, labels, 3, 1)[0])
        assert planted.coloring_conflicts(ring, labels).first()[0] == conflicts and np.allclose(T, C.coloring_compat(3)) == (conflicts == 0)


def dense(edges, seeds, k, setting):
    P = {(r.src, r.dst): r.w for r in propagate.operator(edges, seeds, *setting).collect()}
    n = 6
    A = np.zeros((n, n))
    for (i, j), w in P.items():
        A[i, j] = w
    return A


@pytest.mark.parametrize("setting", [(0.0, 0.0, 0.0), (0.0, 1.0, 0.5)])
def test_echo_radius_limit_and_convergence(micro, setting):
    """Against the eigenvalues of the dense nk x nk update."""
    edges, labels = micro
    seeds = labels.filter("node in (0, 3)")
    A, Kc = dense(edges, seeds, 3, setting), center(K)

    def whole(eps):
        return radius(eps * np.kron(A, Kc.T) - eps**2 * np.kron(np.diag((A * A.T).sum(1)), (Kc @ Kc).T))

    P = propagate.operator(edges, seeds, *setting)
    assert propagate.operator_radius(P, K, 0.4, rounds=80, tol=1e-6) == pytest.approx(whole(0.4), rel=0.02)
    assert propagate.operator_radius(P, K, 0.4, echo=False, rounds=80, tol=1e-6) == pytest.approx(radius(0.4 * np.kron(A, Kc.T)), rel=0.02)
    a, b, g = setting
    limit = propagate.stability_limit(edges, seeds, K, alpha=a, beta=b, gamma=g, echo=True, rounds=60, halvings=8)
    assert whole(limit) == pytest.approx(1, abs=0.05)
    assert propagate.converges(edges, seeds, K, 0.85 * limit, alpha=a, beta=b, gamma=g, echo=True, rounds=80)
    assert not propagate.converges(edges, seeds, K, 1.2 * limit, alpha=a, beta=b, gamma=g, echo=True, rounds=80)
    plain = propagate.stability_limit(edges, seeds, K, alpha=a, beta=b, gamma=g)
    assert propagate.converges(edges, seeds, K, 0.8 * plain, alpha=a, beta=b, gamma=g) and plain * radius(np.kron(A, Kc.T)) <= 1.01


def test_run_to_a_tolerance(micro):
    edges, labels = micro
    seeds = labels.filter("node in (0, 3, 4)")
    got = {r.node: np.array(r[1:]) for r in propagate.propagate(edges, seeds, K, beta=1.0, eps=0.4, r=200, tol=1e-10).collect()}
    want = propagate.closed_form(edges, seeds, K, beta=1.0, eps=0.4)
    assert all(np.allclose(got[n], want[n], atol=1e-8) for n in want)


def test_closed_form_refuses_instead_of_truncating(spark):
    pairs = [(i, j, 1.0) for i in range(40) for j in range(i)]
    edges = normalise_edges(spark.createDataFrame(pairs, "a long, b long, w double"))
    seeds = spark.createDataFrame([(0, 0)], "node long, cls int")
    with pytest.raises(ValueError, match="120"):
        propagate.closed_form(edges, seeds, K, most=119)
    assert len(propagate.closed_form(edges, seeds, K, eps=0.01, most=120)) == 40


def test_two_class_method_solves_its_system(micro):
    edges, labels = micro
    seeds = labels.filter("node in (0, 1)")
    h, A = 0.08, dense(edges, seeds, 2, (0.0, 0.0, 0.0))
    c1, c2 = 4 * h * h / (1 - 4 * h * h), 2 * h / (1 - 4 * h * h)
    x = np.array([0.5, -0.5, 0, 0, 0, 0])
    want = np.linalg.solve(np.eye(6) + c1 * np.diag(A.sum(1)) - c2 * A, x)
    got = {r.node: r.b0 for r in propagate.two_class(edges, seeds, h, r=60).collect()}
    assert all(got[i] == pytest.approx(want[i], abs=1e-9) for i in range(6))


def test_seed_scaling_changes_the_arg_max(spark):
    """One seed of class 0 against three of class 1, at equal distance: only the scaled walk gives the lone seed its weight."""
    star = normalise_edges(spark.createDataFrame([(0, i, 1.0) for i in range(1, 5)], "a long, b long, w double"))
    seeds = spark.createDataFrame([(1, 0), (2, 1), (3, 1), (4, 1)], "node long, cls int")
    at0 = lambda df: next((r.b0, r.b1) for r in df.collect() if r.node == 0)
    a, b = at0(propagate.restart_walk(star, seeds, 2)), at0(propagate.restart_walk(star, seeds, 2, seed_norm=False))
    assert a[0] == pytest.approx(a[1]) and b[1] > 2 * b[0]


def test_narrow_state_equals_columns(spark, micro):
    edges, labels = micro
    seeds = labels.filter("node in (0, 3, 4)")
    table = spark.createDataFrame([(c, d, float(center(K)[c, d])) for c in range(3) for d in range(3)], "c int, d int, v double")
    wide = {(r.node, c): r[f"b{c}"] for r in propagate.propagate(edges, seeds, K, beta=1.0, eps=0.4, r=6).collect() for c in range(3)}
    narrow = {(r.node, r.cls): r.v for r in propagate.propagate_narrow(edges, seeds, table, 3, beta=1.0, eps=0.4, r=6).collect()}
    assert wide.keys() == narrow.keys() and all(wide[x] == pytest.approx(narrow[x]) for x in wide)


def test_a_step_has_one_exchange_of_messages(micro):
    """Messages, seeds and echo are summed in one aggregation; nothing else moves but the small degree and seed tables."""
    edges, labels = micro
    P = edges.repartition("dst").persist()
    B = propagate.step(P, L.residual(labels, 3), L.residual(labels, 3), center(K), 0.1, None)
    B.collect()
    plan = B._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0]
    assert plan.count("Exchange hashpartitioning(node") == 1
    P.unpersist()


def test_loops_release_what_they_cache(spark, micro):
    edges, labels = micro
    seeds = labels.filter("node in (0, 3, 4)")
    held = lambda: len(list(spark.sparkContext._jsc.getPersistentRDDs().values()))
    before = held()
    propagate.propagate(edges, seeds, K, beta=1.0, eps=0.4, r=6, echo=True, hub_edges=2).collect()
    propagate.pagerank(edges).collect()
    walks.count_matrices(edges, seeds, 3, 5)
    propagate.stability_limit(edges, seeds, K, echo=True, rounds=6, halvings=2)
    propagate.settle_steps(edges, seeds, K, 3).collect()
    assert held() == before


@pytest.mark.parametrize("back", [False, True])
def test_products_of_states_equal_the_chain(spark, back):
    r = np.random.default_rng(12)
    pairs = {(min(a, b), max(a, b)) for a, b in r.integers(0, 40, (120, 2)).tolist() if a != b}
    edges = normalise_edges(spark.createDataFrame([(a, b, 1.0) for a, b in pairs], "a long, b long, w double"))
    seeds = spark.createDataFrame([(i, int(r.integers(0, 3))) for i in range(0, 40, 3)], "node long, cls int")
    chain = walks.hop_counts(edges, seeds, 3, 6, back)
    found = walks.count_matrices(edges, seeds, 3, 6, back)
    for N, M in zip(chain, found, strict=True):
        want = np.zeros((3, 3))
        for row in walks.pair_counts(N, seeds, 3).collect():
            want[row.c, row.d] = row.cnt
        assert (want == M).all()
    other = seeds.filter("node % 2 = 0")
    both = walks.batched_matrices(edges, [seeds, other], 3, 5, back)
    assert all((a == b).all() for a, b in zip(both[0], found, strict=False)) and all((a == b).all() for a, b in zip(both[1], walks.count_matrices(edges, other, 3, 5, back), strict=True))


def test_estimators_in_residual_form(spark, micro):
    from compatgraph.plans import estimate

    edges, labels = micro
    for residual, plain in ((estimate.estimate_onehop(edges, labels, 3, residual=True), estimate.estimate_onehop(edges, labels, 3)), (estimate.estimate_energy(edges, labels, 3, mode="residual", alpha=1.0), estimate.estimate_energy(edges, labels, 3, alpha=1.0))):
        assert np.allclose(residual + 1 / 3, plain) and np.allclose(residual.sum(1), 0)
    T = [np.linalg.matrix_power(K, l) for l in range(1, 6)]
    assert np.allclose(C.fit_powers(T, residual=True)[0] + 1 / 3, K, atol=1e-6)
    seeds = labels.filter("node in (0, 1)")
    report = estimate.estimate_report(edges, seeds, 3, 3)
    assert report.pairs == [2, 0, 2] and report.empty_rows == [[2], [0, 1, 2], [2]]
    assert not np.allclose(estimate.estimate_energy(edges, seeds, 3, alpha=1.0, rows="labelled"), estimate.estimate_energy(edges, seeds, 3, alpha=1.0))


def test_unreached_nodes_favour_no_class(spark):
    labels = spark.createDataFrame([(i, 0) for i in range(4)], "node long, cls int")
    got = L.accuracy(L.hold_out(spark.createDataFrame([(1, 0)], "node long, cls int"), labels, labels.filter("node = 0"))).first()
    assert tuple(got) == (3, 1, 2)


def test_readers_drop_malformed_rows(spark, tmp_path):
    from compatgraph.sources.tables import EDGES, check_schema, read_edges, write_run

    (tmp_path / "a.csv").write_text("src,dst,w\n1,2,0.5\nx,3,1\n4,5\n6,7,2.5,9\n")
    (tmp_path / "a.tsv").write_text("src\tdst\tw\n1\t2\t0.5\n1\t\t3\n")
    (tmp_path / "a.json").write_text('{"src": 1, "dst": 2, "w": 0.5}\n{"src": 1, broken\n{"src": 3, "dst": 4, "w": 1}\n')
    read = lambda x, kind: sorted(tuple(r) for r in read_edges(spark, str(tmp_path / x), kind).collect())
    assert read("a.csv", "csv") == [(1, 2, 0.5), (6, 7, 2.5)] and read("a.tsv", "tsv") == [(1, 2, 0.5)] and read("a.json", "json") == [(1, 2, 0.5), (3, 4, 1.0)]
    with pytest.raises(TypeError, match="dst"):
        check_schema(spark.createDataFrame([(1, "2", 1.0)], "src long, dst string, w double"))
    edges = spark.createDataFrame([(1, 2, 1.0)], EDGES)
    for run, df in (("a", edges), ("b", edges), ("a", edges.unionByName(edges))):
        write_run(df, str(tmp_path / "runs"), run)
    assert sorted((r.run, r["count"]) for r in spark.read.parquet(str(tmp_path / "runs")).groupBy("run").count().collect()) == [("a", 2), ("b", 1)]


def test_bucketed_edges_are_not_exchanged(spark, micro, tmp_path):
    from compatgraph.sources.tables import write_bucketed

    edges, labels = micro
    write_bucketed(edges, "bucketed_test_edges", 4)
    try:
        P = spark.table("bucketed_test_edges")
        B = propagate.step(P, None, L.residual(labels, 3).hint("merge"), center(K), 0.1, None)
        assert "Exchange hashpartitioning(dst" not in B._jdf.queryExecution().executedPlan().toString().replace("Exchange hashpartitioning(dst#", "state", 1)
        assert sorted(map(tuple, B.collect())) == sorted(map(tuple, propagate.step(edges, None, L.residual(labels, 3), center(K), 0.1, None).collect()))
    finally:
        spark.sql("drop table bucketed_test_edges")


def test_planted_source_draws_by_its_strengths(spark):
    from compatgraph.sources import planted_source

    planted_source.register(spark)
    read = lambda parts: spark.read.format("planted").options(nodes=6_000, degree=10, strength=8, partitions=parts).load()
    arcs = read(3)
    assert arcs.count() == pytest.approx(30_000, rel=0.01) and arcs.filter("dst < 0 or dst >= 6000 or src = dst").count() == 0
    got = np.zeros((3, 3))
    for r in arcs.groupBy((F.col("src") % 3).alias("c"), (F.col("dst") % 3).alias("d")).agg(F.count("*").alias("n")).collect():
        got[r.c, r.d] = r.n
    assert np.allclose(got / got.sum(1, keepdims=True), K, atol=0.02)


def test_step_has_no_python_and_pushes_columns(spark, data):
    from compatgraph import registry

    plan = registry.queries()["prop_recommended"](spark, data)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Cartesian" not in plan
    scan = registry.queries()["edges_trade"](spark, data)._jdf.queryExecution().executedPlan().toString()
    assert "o_totalprice" not in scan


def test_stream_equals_batch(spark, data, tmp_path):
    from compatgraph.sources.tables import table
    from compatgraph.streaming import pairs as P

    events = table(spark, data, "events", "event_id", "ts", "user_id", "event_type")
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    running = P.RunningCompat(sorted(r[0] for r in events.select("event_type").distinct().collect()))
    source = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    seen = []
    q = P.class_steps(source).writeStream.foreachBatch(lambda df, i: (running(df, i), seen.append(df.count())) and None).option("checkpointLocation", str(tmp_path / "cp")).start()
    q.processAllAvailable()
    q.stop()
    batch = P.class_steps(events)
    assert sum(seen) == batch.count() and running.M.sum() == 2 * batch.count()


def test_replayed_batches_count_once(spark):
    from compatgraph.streaming.pairs import RunningCompat

    running, steps = RunningCompat(["a", "b"]), spark.createDataFrame([("a", "b"), ("a", "a")], "a string, b string")
    for epoch in (0, 0, 1, 0, 1):
        running(steps, epoch)
    assert running.M.sum() == 2 * 2 * 2 and len(running.drift) == 2


def _streamed(spark, df, path, build, mode="append"):
    """Rows of a stream over the files of ``path``, one file a micro-batch, by way of a memory sink; and the query."""
    source = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(path))
    name = f"out_{abs(hash(str(path))) % 10**9}"
    q = build(source).writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    return spark.table(name), q


def test_stream_windows_drop_late_rows_and_repeats(spark, tmp_path):
    from datetime import datetime, timedelta

    from compatgraph.streaming import pairs as P

    day = lambda n, h=0: datetime(2024, 1, 1) + timedelta(days=n, hours=h)
    schema = "event_id long, ts timestamp, user_id long, event_type string, a string, b string"
    files = [[(1, day(0, 1), 1, "x", "x", "y"), (1, day(0, 1), 1, "x", "x", "y"), (2, day(0, 2), 1, "y", "x", "y")], [(3, day(6), 1, "x", "x", "x")], [(4, day(0, 3), 1, "x", "x", "y"), (5, day(6, 1), 1, "y", "x", "x"), (3, day(6), 1, "x", "x", "x")], [(6, day(12), 1, "x", "x", "x")], [(7, day(12, 1), 1, "x", "x", "x")]]
    for i, f in enumerate(files):
        old = set((tmp_path / "in").glob("*.parquet"))
        spark.createDataFrame(f, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        for file in set((tmp_path / "in").glob("*.parquet")) - old:  # a source takes files by their times
            os.utime(file, (1_700_000_000 + 60 * i,) * 2)
    df = spark.read.parquet(str(tmp_path / "in"))
    out, q = _streamed(spark, df, tmp_path / "in", lambda e: P.windowed(e.select("ts", "a", "b"), late="1 day"))
    counts = {(r.start.day, r.a, r.b): r.n for r in out.collect()}
    assert counts[1, "x", "y"] == 3 and counts[7, "x", "x"] == 3  # the row of day 0 that came after day 6 is not there
    assert P.dropped_late(q) == 1
    q.stop()
    once, q = _streamed(spark, df, tmp_path / "in", lambda e: P.deduplicated(e, "2 days").select("event_id"))
    assert sorted(r.event_id for r in once.collect()) in ([1, 2, 3, 5, 6, 7], [1, 2, 3, 4, 5, 6, 7])
    q.stop()
    classes = spark.createDataFrame([("x", 0), ("y", 1)], "name string, cls int")
    typed, q = _streamed(spark, df, tmp_path / "in", lambda e: P.with_classes(e, classes).select("event_id", "cls"))
    assert typed.count() == 9 and {(r.event_id, r.cls) for r in typed.collect()} >= {(1, 0), (2, 1)}
    q.stop()
    ses, q = _streamed(spark, df, tmp_path / "in", lambda e: P.sessions(e.select("ts", "user_id"), "90 minutes"))
    assert {(r.start.day, r.n) for r in ses.collect()} >= {(1, 3)}
    q.stop()


def test_weighted_walks_equal_enumeration(spark):
    pairs = [(0, 1, 2.0), (1, 2, 3.0), (2, 0, 5.0), (2, 3, 0.5), (3, 4, 4.0), (4, 2, 1.5)]
    arcs = {(a, b): w for a, b, w in pairs} | {(b, a): w for a, b, w in pairs}
    edges = normalise_edges(spark.createDataFrame(pairs, "a long, b long, w double"))
    seeds = spark.createDataFrame([(0, 0), (2, 1), (4, 0)], "node long, cls int")
    cls = {0: 0, 2: 1, 4: 0}
    for l, N in enumerate(walks.weighted_hop_counts(edges, seeds, 2, 4), 1):
        want = np.zeros((5, 2))
        for path in itertools.product(range(5), repeat=l + 1):
            steps = list(itertools.pairwise(path))
            if all(s in arcs for s in steps) and all(x != z for x, z in zip(path, path[2:])) and path[-1] in cls:
                want[path[0], cls[path[-1]]] += np.prod([arcs[s] for s in steps])
        got = np.zeros((5, 2))
        for r in N.collect():
            got[r.node] = r[1:]
        assert np.allclose(got, want)


@pytest.mark.parametrize("most", [1, 2, 100])
def test_spread_hubs_changes_no_belief(spark, most):
    star = normalise_edges(spark.createDataFrame([(0, i, 1.0 + i) for i in range(1, 12)], "a long, b long, w double"))
    seeds = spark.createDataFrame([(1, 0), (0, 1), (5, 2)], "node long, cls int")
    plain, spread = ({r.node: r[1:] for r in propagate.propagate(star, seeds, K, beta=1.0, eps=0.3, r=3, echo=True, hub_edges=h).collect()} for h in (None, most))
    assert plain.keys() == spread.keys() and all(np.allclose(plain[n], spread[n]) for n in plain)


def test_laplacian_smoothness_is_the_sum_over_edges(spark, micro):
    edges, _ = micro
    b = spark.createDataFrame([(i, float(i), -float(i)) for i in range(6)], "node long, b0 double, b1 double")
    want = sum(2 * (i - j) ** 2 for i, j in RING)
    assert propagate.smoothness(edges, b, np.eye(2)).first()[0] == pytest.approx(want)


def test_nearest_refuses_what_is_too_large(spark):
    from compatgraph.sources.tables import nearest

    v = spark.createDataFrame([(i, [1.0, float(i)]) for i in range(5)] + [(9, None)], "vec_id long, embedding array<float>")
    assert {(r.a, r.b) for r in nearest(v, 1).collect()} == {(0, 1), (1, 2), (2, 3), (3, 4), (4, 3)}
    with pytest.raises(ValueError):
        nearest(v, 1, most=4)
    hashed = nearest(v, 4, bits=2, tables=8)
    assert hashed.count() == hashed.select("a", "b").distinct().count() <= 20 and nearest(v.limit(0), 2, bits=2).count() == 0


def test_turns_of_long_conversations_stay_apart(spark, tmp_path):
    from compatgraph.sources.tables import TURN_SPAN, turn_labels, turns

    rows = [(c, t, ("assistant", "system")[c - 1]) for c in (1, 2) for t in range(TURN_SPAN + 3)]
    spark.createDataFrame(rows, "conv_id long, turn long, role string").write.parquet(f"{tmp_path}/conversations.parquet")
    labels, edges = {r.node: r.cls for r in turn_labels(spark, tmp_path).collect()}, turns(spark, tmp_path).collect()
    assert len(labels) == len(rows) and labels[TURN_SPAN] == 0 and labels[2 * TURN_SPAN] == 1
    assert len(edges) == 2 * 2 * (TURN_SPAN + 2) and all(labels[r.src] == labels[r.dst] and r.w == 1 for r in edges)


def test_nearest_is_exact_beyond_ten_thousand_vectors(spark):
    from compatgraph.sources.tables import nearest

    r = np.random.default_rng(6)
    x = r.standard_normal((10_500, 8)).astype(np.float32)
    x[:600] = x[0]  # ties by id
    got = {}
    for row in nearest(spark.createDataFrame(list(enumerate(x.tolist())), "vec_id long, embedding array<float>"), 3).collect():
        got.setdefault(row.a, []).append((row.pos, row.b, row.cos))
    assert len(got) == len(x)
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1)[:, None]
    for a in [*range(5), *range(590, 610), *range(9_000, 10_500, 50)]:
        cos = (unit @ unit[a]).round(6)
        cos[a] = -2
        want = sorted(range(len(x)), key=lambda b: (-cos[b], b))[:3]
        assert [b for _, b, _ in sorted(got[a])] == want and np.allclose([c for *_, c in sorted(got[a])], cos[want], atol=2e-6)


def test_brute_force_walks_leave_out_what_leads_nowhere(spark):
    """The leaves of a star would meet each other in 3.6 thousand million walks of two hops."""
    star = spark.range(1, 60_001).selectExpr("0L as src", "id as dst", "1.0D as w")
    path = spark.createDataFrame([(0, -1, 1.0), (-1, -2, 1.0)], "src long, dst long, w double")
    edges = star.unionByName(path)
    edges = edges.unionByName(edges.selectExpr("dst as src", "src as dst", "w"))
    got = walks.enumerate_walks(edges, 3)
    assert got.filter("n = 1").count() == 120_000 and got.filter("src = -2 or dst = -2").count() == 120_000  # a leaf, 0, -1, -2 and back
    arcs = spark.createDataFrame([(0, 1, 1.0), (1, 2, 1.0), (2, 3, 1.0), (1, 0, 1.0)], "src long, dst long, w double")  # one way
    assert [tuple(r) for r in walks.enumerate_walks(arcs, 3).collect()] == [(0, 3, 1)]
    assert sorted(tuple(r) for r in walks.enumerate_walks(arcs, 3, True).collect()) == [(0, 0 + 1, 1), (0, 3, 1), (1, 0, 1), (1, 2, 1)]


def test_pagerank_takes_the_echo_from_sums(spark, micro, monkeypatch):
    """The echo diagonal is not a join of edges to edges, which writes them twice more."""
    def no_join(edges):
        raise AssertionError("edges meet edges")

    monkeypatch.setattr(propagate, "echo_diagonal", no_join)
    edges = micro[0].withColumn("w", F.lit(1.0) + F.pmod(F.col("src") * F.col("dst"), F.lit(3)))
    rows = edges.collect()
    at = {n: i for i, n in enumerate(sorted({r.src for r in rows}))}
    A = np.zeros((len(at), len(at)))
    for r in rows:
        A[at[r.src], at[r.dst]] = r.w
    P = A / A.sum(0)
    for echo in (False, True):
        f = np.full(len(at), 1 / len(at))
        for _ in range(4):
            f = 0.15 / len(at) + 0.85 * P @ f - echo * 0.85**2 * (P * P.T).sum(1) * f
        assert {r.node: pytest.approx(f[at[r.node]]) for r in propagate.pagerank(edges, echo=echo).collect()} == {r.node: r.b0 for r in propagate.pagerank(edges, echo=echo).collect()}


def test_hashed_neighbours_meet_in_blocks(spark, monkeypatch):
    """One large bucket of copies: a bucket's pairs are never rows, and blocks of queries lose none."""
    from compatgraph.sources import tables as T

    monkeypatch.setattr(T, "QUERIES", 7)
    rng = np.random.default_rng(3)
    x = rng.standard_normal((120, 6)).astype(np.float32)
    x[40:100] = x[40]
    vectors = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    planes = np.random.default_rng(1).standard_normal((2, 2, 6)).round(6)
    keys = [[tuple((x[i].astype(float) @ p) > 0 for p in planes[t]) for t in range(2)] for i in range(120)]
    d = x.astype(float) / np.linalg.norm(x.astype(float), axis=1)[:, None]
    want = set()
    for a in range(120):
        met = [b for b in range(120) if b != a and any(keys[a][t] == keys[b][t] for t in range(2))]
        want |= {(a, b, p) for p, b in enumerate(sorted(met, key=lambda b: (-round(d[a] @ d[b], 6), b))[:5], 1)}
    df = T.nearest(vectors, 5, bits=2, tables=2)
    assert {(r.a, r.b, r.pos) for r in df.collect()} == want
    assert "SortMergeJoin" not in df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name, least", [("closed_form_micro", 4), ("compat_rows", 1), ("planted_source", 1)])
def test_small_queries_work_on_the_given_tables(spark, data, tmp_path, name, least):
    """What they return follows the tables: without their rows it would be the same as with them."""
    import shutil

    from compatgraph import registry

    d = shutil.copytree(data, tmp_path / "sf")
    for t, condition in (("customer", "c_custkey % 2 = 0"), ("events", "event_id % 3 > 0")):
        os.remove(d / f"{t}.parquet") if (d / f"{t}.parquet").is_file() else shutil.rmtree(d / f"{t}.parquet")
        spark.read.parquet(f"{data}/{t}.parquet").filter(condition).write.parquet(str(d / f"{t}.parquet"))
    whole, part = ({tuple(r) for r in registry.queries()[name](spark, str(x)).collect()} for x in (data, d))
    assert len(part) >= least and whole != part
    if name == "planted_source":
        of = {r.c_custkey for r in spark.read.parquet(f"{d}/customer.parquet").collect()}
        assert {x for r in part for x in r} <= of and any(x not in of for r in whole for x in r)


def test_the_budget_reads_the_keys(spark, data):
    from unittest import mock

    from compatgraph import registry

    seen, real = [], type(spark.range(1)).agg
    with mock.patch.object(type(spark.range(1)), "agg", lambda self, *a: seen.append(real(self, *a)) or seen[-1]):
        registry.queries()["planted_budget"](spark, data)
    assert any("ReadSchema: struct<c_custkey" in x._jdf.queryExecution().executedPlan().toString() or "c_custkey" in x._jdf.queryExecution().executedPlan().toString() for x in seen)


def test_runs_side_by_side_equal_single_runs(spark, micro):
    edges, labels = micro
    sets, K = [labels.limit(2).localCheckpoint(), labels.localCheckpoint()], strength_compat(8)
    runs = [{"seeds": i, "K": K, "eps": 0.3, "r": r, **more} for i, r, more in ((0, 2, {}), (1, 3, {"beta": 1.0, "gamma": 0.5, "echo": True}), (0, 3, {"alpha": 0.5, "beta": 0.5, "gamma": 1.0}))]
    got = {x.node: x for x in propagate.propagate_many(edges, sets, runs, 3).collect()}
    for j, x in enumerate(runs):
        own = {k: v for k, v in x.items() if k not in ("seeds", "K")}
        want = {r.node: tuple(r)[1:] for r in propagate.propagate(edges, sets[x["seeds"]], K, **own).collect()}
        have = {n: tuple(r[f"b{j}_{c}"] for c in range(3)) for n, r in got.items() if r[f"b{j}_0"] is not None}
        assert have == {n: pytest.approx(v, abs=1e-12) for n, v in want.items()}
    found = propagate.spectral_radii(edges, sets[0], [0.0, 0.5])
    assert found == [pytest.approx(propagate.spectral_radius(propagate.operator(edges, sets[0], 0, 0, g)), abs=1e-9) for g in (0.0, 0.5)]


def test_wiring_hashes_a_stub_twice_and_keeps_budgets(spark):
    """A stub is hashed for the bucket counts and for its place, not again for a filter of the join; stubs beyond a budget are left out."""
    M = np.array([[1, 4, 1], [2, 1, 3], [5, 2, 2]])
    nodes = spark.createDataFrame([(10 * c + i, c) for c in range(3) for i in range(3)], "node long, cls int")
    out, into = planted.assign_degrees(nodes, M.sum(1).tolist()), planted.assign_degrees(nodes, M.sum(0).tolist())
    arcs = planted.wire(out, into, M)
    assert arcs._jdf.queryExecution().optimizedPlan().toString().count("md5(") == 4
    cls, got = F.floor(F.col("src") / 10), np.zeros((3, 3), int)
    assert arcs.filter((cls != F.col("c")) | (F.floor(F.col("dst") / 10) != F.col("d"))).count() == 0
    for r in arcs.groupBy("c", "d").agg(F.count("*").alias("n")).collect():
        got[r.c, r.d] = r.n
    assert (got == M).all()
    fewer = M - np.eye(3, dtype=int)
    assert planted.wire(out, into, fewer).count() == fewer.sum()


def test_cached_edges_are_in_the_order_of_the_steps(spark, data):
    """No step of the phases sorts or moves the edges: they are cached by sending node and in its order."""
    from compatgraph import workloads as W

    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with W.planted(spark, data, 8, 10, 0.1) as (edges, labels, _):
            assert edges.count() == 1_500
            sent = propagate.send(edges, labels.select("node", F.lit(1.0).alias("b0")), 1)
            assert sent.agg(F.sum("b0")).first()[0] == 1_500
            sent.collect()
            plan = sent._jdf.queryExecution().executedPlan().toString().split("== Initial Plan ==")[0].split("InMemoryRelation")[0]
            assert "SortMergeJoin" in plan and "Sort [" not in plan.split("SortMergeJoin")[1].split("TableCacheQueryStage")[0]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_scalability_plants_side_by_side(spark, data, monkeypatch):
    """All graphs are under way at once, and no phase is timed before all are there."""
    import threading

    from compatgraph import workloads as W

    all_there, done = threading.Barrier(3, timeout=20), []
    monkeypatch.setattr(W, "_graph", lambda spark, d, h, degree, name, key: (all_there.wait(), done.append(name)))
    monkeypatch.setattr(W, "phases", lambda spark, d, name, key: (done.append("phases"), spark.createDataFrame([(name,)], "phase string"))[1])
    got = W.scalability(spark, data).collect()
    assert sorted(done[:3]) == ["customer", "orders", "part"] and done[3:] == ["phases"] * 3
    assert [r["keys"] for r in got] == ["customer", "part", "orders"]


def jobs(spark, group: str, action):
    spark.sparkContext.setJobGroup(group, group)
    try:
        return action(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def test_rounds_over_blocks_are_few_jobs_and_the_same_numbers(spark, monkeypatch):
    """Many parts, negative numbers as nodes, weights, seeds without edges; forty rounds are not forty jobs."""
    from compatgraph.plans import blocks

    monkeypatch.setattr(blocks, "LEAST", 4)
    rng = np.random.default_rng(3)
    A = np.triu((rng.random((30, 30)) < 0.2) * rng.integers(1, 4, (30, 30)), 1).astype(float)
    A += A.T
    name = lambda i: int(i) * 7_919_000_000_003 - 10**14
    edges = spark.createDataFrame([(name(i), name(j), float(A[i, j])) for i, j in zip(*np.nonzero(A), strict=True)], "src long, dst long, w double").localCheckpoint()
    labels = spark.createDataFrame([*[(name(i), i % 3) for i in range(0, 30, 4)], (5, 1)], "node long, cls int").localCheckpoint()
    own = blocks.Blocks(edges, labels)
    assert own.n == 4 and sorted(n for _, x in own.rdd.collect() for n in x["nodes"].tolist()) == sorted({name(i) for i in range(30) if A[i].any()} | {r.node for r in labels.collect()})
    (root, _), used = jobs(spark, "perron", lambda: blocks.perron(own, 40, 0.0))
    assert root == pytest.approx(max(abs(np.linalg.eigvalsh(A))), rel=1e-3) and used <= 10
    lopsided = edges.filter("src < dst or src % 2 = 0")
    B = np.where((np.arange(30)[:, None] < np.arange(30)[None]) | (np.array([name(i) % 2 == 0 for i in range(30)])[:, None]), A, 0)
    assert propagate.spectral_radius(lopsided, 40, 0.0) == pytest.approx(max(abs(np.linalg.eigvals(B))), rel=0.02)
    K = strength_compat(8)
    runs = [{"seeds": 0, "K": M, "eps": e, "r": r, "beta": 1.0, "gamma": 0.5} for M, e, r in ((K, 0.3, 2), (np.eye(3), 0.9, 4), (K, 0.0, 3))]
    found, used = jobs(spark, "many", lambda: {x.node: x for x in propagate.propagate_many(edges, [labels], runs, 3, own).collect()})
    assert used <= 10 and found[5].b0_1 == pytest.approx(2 / 3)
    for j, x in enumerate(runs):
        options = {k: v for k, v in x.items() if k not in ("seeds", "K")}
        want = {r.node: pytest.approx(tuple(r)[1:], abs=1e-12) for r in propagate.propagate(edges, labels, x["K"], **options).collect()}
        assert {n: tuple(r[f"b{j}_{c}"] for c in range(3)) for n, r in found.items() if r[f"b{j}_0"] is not None} == want
        assert {r.node: tuple(r)[1:] for r in propagate.propagate(edges, labels, x["K"], held=own, **options).collect()} == want
    with pytest.raises(Exception, match="do not hold"):
        propagate.propagate_many(edges, [spark.createDataFrame([(77, 0)], "node long, cls int")], runs, 3, own)
    own.drop()
    none = edges.filter("w < 0")
    assert propagate.spectral_radius(none) == 0.0 and propagate.propagate_many(none, [labels], runs, 3).filter("b0_0 is not null").count() == labels.count()


def test_counts_over_blocks_are_the_same(spark, monkeypatch):
    from compatgraph.plans import blocks

    monkeypatch.setattr(blocks, "LEAST", 32)
    edges, labels, _ = planted.planted_graph(spark.range(90).withColumnRenamed("id", "node"), K, 6)
    edges = edges.localCheckpoint()
    sets = [labels.filter(F.col("node") % 3 == i).localCheckpoint() for i in (0, 1)]
    own = blocks.Blocks(edges, labels)
    assert own.n == 4
    for back in (False, True):
        want = walks.batched_matrices(edges, sets, 3, 5, back)
        got, used = jobs(spark, f"counts{back}", lambda back=back: walks.batched_matrices(edges, sets, 3, 5, back, held=own))
        assert used <= 3 and np.array_equal(got, want)
    own.drop()


def test_repair_hashes_the_arcs_once_a_round(spark, monkeypatch):
    """Later passes tell the drawn arcs by their ends; the sound arcs left over are those that the hash left."""
    seen = []
    real = planted.cut
    monkeypatch.setattr(planted, "cut", lambda df: seen.append(df._jdf.queryExecution().optimizedPlan().toString().split("InMemoryRelation")[0]) or real(df))
    arcs = spark.range(4_000).select((F.col("id") % 61).alias("src"), (F.col("id") * 7 % 67 + 100).alias("dst"), F.lit(0).alias("c"), F.lit(1).alias("d")).localCheckpoint()
    arcs = arcs.unionByName(arcs.limit(50).localCheckpoint()).localCheckpoint()
    repaired, left = planted.repair(arcs, rounds=2)
    assert repaired.count() == 4_050 and seen[-1].count("md5(s1.") == 0 and "md5" not in seen[-1]
