"""Named queries of the engine and the SQL that DuckDB can express for them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import oracle as O
from .functions.compat import center, identity_compat, strength_compat
from .operators import labels as L
from .operators import scaling as S
from .plans import estimate, planted, propagate, walks
from .plans.lineage import shared_dir
from .sources import planted_source
from .sources import tables as T
from .streaming import pairs as stream
from .workloads import WORKLOADS

QUERIES: dict = dict(WORKLOADS)
SQL: dict[str, str] = {}
K3, K5 = strength_compat(8), np.full((5, 5), 0.1) + 0.5 * np.eye(5)
HALF = 0.5


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


def turns(spark, d, f: float | None = HALF):
    labels = T.turn_labels(spark, d)
    return T.turns(spark, d), labels, labels if f is None else L.hide_labels(labels, f)


def trade(spark, d, f: float = HALF):
    labels = T.trade_labels(spark, d)
    return T.trade(spark, d), labels, L.hide_labels(labels, f)


def rounded(df: DataFrame, k: int, digits: int = 6) -> DataFrame:
    return df.select("node", *[(F.round(f"b{c}", digits) + 0.0).alias(f"b{c}") for c in range(k)])


# --- graphs and labels
for _name, _build in (("trade", T.trade), ("copart", T.copart), ("turns", T.turns), ("steps", T.steps), ("tree", T.tree), ("docs", T.same_text), ("pages", T.pages)):
    query(f"edges_{_name}", O.graph(_name).split(", labels as")[0] + " select * from edges")(_build)
for _name, _build in (("trade", T.trade), ("copart", T.copart)):
    query(f"deg_{_name}", f"with {O.EDGES[_name]}, {O.BOTH} select src as node, sum(w) as deg from edges group by src")(lambda s, d, b=_build: S.degrees(b(s, d)))
query("one_hot_turns", O.graph("turns") + " select node, (cls = 0)::bigint as b0, (cls = 1)::bigint as b1, (cls = 2)::bigint as b2 from labels")(lambda s, d: L.one_hot(T.turn_labels(s, d), 3))
query("hide_md5", O.graph("turns", HALF) + " select * from seeds")(lambda s, d: turns(s, d)[2])
query("residual_turns", O.graph("turns", HALF) + O.residual(3) + f" select {O.rounded(3)} from x")(lambda s, d: rounded(L.residual(turns(s, d)[2], 3), 3))
query("modulate_turns", O.graph("turns", HALF) + O.residual(3) + ", y as (select node, " + ", ".join(f"{e} as b{i}" for i, e in enumerate(O.linear(K3))) + f" from x) select {O.rounded(3)} from y")(lambda s, d: rounded(L.residual(turns(s, d)[2], 3).select("node", *L.modulate(3, K3)), 3))


@query("shift_invariance", SQL["modulate_turns"])
def shift_invariance(spark, d):
    """Residual rows under K less a constant; the SQL takes K itself, and the rows are the same."""
    return rounded(L.residual(turns(spark, d)[2], 3).select("node", *L.modulate(3, center(K3))), 3)


query("row_sums", O.graph("turns", HALF) + O.residual(3) + ", y as (select " + ", ".join(f"{e} as b{i}" for i, e in enumerate(O.linear(K3))) + " from x) select round(max(abs(b0 + b1 + b2))::double, 9) + 0.0::double as deviation from y")(
    lambda s, d: L.row_sum_deviation(L.residual(turns(s, d)[2], 3).select("node", *L.modulate(3, K3)), 3).select((F.round("deviation", 9) + 0.0).alias("deviation"))
)

# --- scaling and clamping
_W = " select src, dst, round(w, 9) + 0.0 as w from p"
nine = lambda df: df.select("src", "dst", (F.round("w", 9) + 0.0).alias("w"))
for _name, (_a, _b) in {"raw": S.RAW, "row": S.ROW, "col": S.COL, "sym": S.SYM, "other": (0.25, 0.5)}.items():
    query(f"scale_{_name}", O.graph("trade", HALF) + O.scaled(_a, _b) + _W)(lambda s, d, a=_a, b=_b: nine(S.scale_edges(T.trade(s, d), a, b)))
for _name, _g in (("hard", 1.0), ("half", 0.5), ("soft", 0.0)):
    query(f"clamp_{_name}", O.graph("trade", HALF) + O.scaled(0.0, 1.0, _g) + _W)(lambda s, d, g=_g: nine(propagate.operator(*trade(s, d)[::2], 0.0, 1.0, g)))


@query("clamp_node", O.graph("trade", HALF) + " select e.src, e.dst, round(w * (1 - coalesce((s.cls + 1) / 5.0, 0)), 9) + 0.0 as w from edges e left join seeds s on s.node = e.src")
def clamp_node(spark, d):
    edges, _, seeds = trade(spark, d)
    return nine(S.clamp_edges(edges, seeds.select("node", ((F.col("cls") + 1) / 5.0).alias("g")), None))


@query("echo_diag", O.graph("trade", HALF) + O.scaled(0.0, 1.0, 0.5) + " select a.src as node, round(sum(a.w * b.w), 9) + 0.0 as q from p a join p b on a.src = b.dst and a.dst = b.src group by a.src")
def echo_diag(spark, d):
    return S.echo_diagonal(propagate.operator(*trade(spark, d)[::2], 0.0, 1.0, 0.5)).select("node", (F.round("q", 9) + 0.0).alias("q"))


query("echo_diag_closed", SQL["echo_diag"])(lambda s, d: (lambda e, _, x: S.echo_diagonal_closed(e, x, 0.0, 1.0, 0.5))(*trade(s, d)).select("node", (F.round("q", 9) + 0.0).alias("q")))

# --- the family
EPS = {True: 0.0517, False: 0.5113}  # no round numbers: results then lie on no rounding tie
for _name, _set in propagate.members().items():
    _K = identity_compat(3) if _set.get("identity") else K3
    _eps = EPS[_set["alpha"] + _set["beta"] == 0]
    _sql = O.graph("turns", HALF) + O.scaled(_set["alpha"], _set["beta"], _set["gamma"]) + O.residual(3) + O.iterate(center(_K), _eps, 4, _set.get("echo", False)) + f" select {O.rounded(3)} from s4"
    query(f"prop_{_name}", _sql)(lambda s, d, n=_name, e=_eps: rounded(propagate.member(n, *turns(s, d)[::2], K3, eps=e, r=4), 3))
query("prop_trade_col", O.graph("trade", HALF) + O.scaled(0.0, 1.0, 0.5) + O.residual(5) + O.iterate(center(K5), 0.5, 3) + f" select {O.rounded(5)} from s3")(lambda s, d: rounded(propagate.propagate(*trade(s, d)[::2], K5, beta=1.0, gamma=0.5, eps=0.5, r=3), 5))
_two = O.graph("turns", HALF).replace("then 1 else 2 end", "then 0 else 1 end")
query("prop_two_class", _two + O.scaled(0, 0) + O.residual(2) + O.iterate([[-0.3, 0.3], [0.3, -0.3]], 0.2, 4, True) + f" select {O.rounded(2)} from s4")(
    lambda s, d: rounded(propagate.propagate(*(lambda e, lab: (e, L.hide_labels(lab.withColumn("cls", (F.col("cls") > 1).cast("int")), HALF)))(T.turns(s, d), T.turn_labels(s, d)), np.array([[0.2, 0.8], [0.8, 0.2]]), eps=0.2, r=4, echo=True), 2)
)


@query("prop_narrow", SQL["prop_recommended"])
def prop_narrow(spark, d):
    """The recommended member with a state of (node, cls, v) rows."""
    edges, _, seeds = turns(spark, d)
    K = spark.createDataFrame([(c, e, float(center(K3)[c, e])) for c in range(3) for e in range(3)], "c int, d int, v double")
    B = propagate.propagate_narrow(edges, seeds, K, 3, beta=1.0, gamma=0.5, eps=EPS[False], r=4)
    return rounded(B.groupBy("node").pivot("cls", [0, 1, 2]).agg(F.sum("v")).toDF("node", "b0", "b1", "b2"), 3)


# --- the members with the factors of the literature
_ONE = ", x as (select node, " + ", ".join(f"(cls = {c})::int::double as b{c}" for c in range(3)) + " from seeds)"
_SHARE = ", n as (select cls, count(*) as n from seeds group by cls), x as (select node, " + ", ".join(f"(s.cls = {c})::int / n::double as b{c}" for c in range(3)) + " from seeds s join n using (cls))"
for _name, _scaling, _gamma, _x, _a, _keep, _run in (
    ("harmonic", S.ROW, 1.0, _ONE, 1.0, 1.0, lambda e, x: propagate.harmonic(e, x, 3)),
    ("consistency", S.SYM, 0.0, _ONE, 0.9, 1 - 0.9, lambda e, x: propagate.consistency(e, x, 3)),
    ("neighborhood", S.ROW, 0.0, _ONE, 0.9, 1 - 0.9, lambda e, x: propagate.neighborhood(e, x, 3)),
    ("restart_walk", S.COL, 0.0, _SHARE, 0.9, 1 - 0.9, lambda e, x: propagate.restart_walk(e, x, 3)),
    ("restart_walk_raw", S.COL, 0.0, _ONE, 0.9, 1 - 0.9, lambda e, x: propagate.restart_walk(e, x, 3, seed_norm=False)),
):
    query(f"lit_{_name}", O.graph("turns", HALF) + O.scaled(*_scaling, _gamma) + _x + O.iterate(np.eye(3), _a, 4, keep=_keep) + f" select {O.rounded(3, 9)} from s4")(lambda s, d, f=_run: rounded(f(*turns(s, d)[::2]), 3, 9))
_C1, _C2 = 4 * 0.01 / (1 - 4 * 0.01), 2 * 0.1 / (1 - 4 * 0.01)
query(
    "lit_two_class",
    _two + ", dg as (select src as node, sum(w) as deg from edges group by src), x as (select node, case when cls = 0 then 0.5 else -0.5 end::double as b0 from seeds)"
    + "".join(f", s{i} as materialized (select node, sum(b0) as b0 from (select * from x union all select e.src, {_C2!r} * sum(e.w * v.b0) from edges e join {'x' if i == 1 else f's{i - 1}'} v on v.node = e.dst group by e.src union all select v.node, {-_C1!r} * dg.deg * v.b0 from {'x' if i == 1 else f's{i - 1}'} v join dg using (node)) group by node)" for i in range(1, 11))
    + " select node, round(b0, 6) + 0.0 as b0 from s10",
)(lambda s, d: rounded(propagate.two_class(T.turns(s, d), L.hide_labels(T.turn_labels(s, d).withColumn("cls", (F.col("cls") > 1).cast("int")), HALF)), 1))


def _vote_sql(r: int) -> str:
    out = O.graph("turns", HALF) + ", x as (select node, (cls = 0)::double as b0, (cls = 1)::double as b1, (cls = 2)::double as b2 from seeds)"
    for i in range(1, r + 1):
        last = "x" if i == 1 else f"s{i - 1}"
        out += f", g{i} as (select e.src as node, sum(w * b0) as b0, sum(w * b1) as b1, sum(w * b2) as b2 from edges e join {last} v on v.node = e.dst where e.src not in (select node from seeds) group by e.src), s{i} as materialized (select * from x union all select node, b0 / (b0 + b1 + b2), b1 / (b0 + b1 + b2), b2 / (b0 + b1 + b2) from g{i})"
    return out + f" select {O.rounded(3)} from s{r}"


query("prop_rnc_norm", _vote_sql(4))(lambda s, d: rounded(propagate.vote_normalised(*turns(s, d)[::2], 3, 4), 3))


def _rank_sql(echo: bool) -> str:
    out = O.graph("trade", HALF) + O.scaled(0.0, 1.0) + ", z as (select distinct src as node from edges), n as (select count(*) as n from z), x as (select node, 0.15 / n as b0 from z, n), x0 as (select node, 1.0 / n as b0 from z, n)"
    return out + O.iterate([[1.0]], 0.85, 4, echo, "x0") + " select node, round(b0, 9) + 0.0 as b0 from s4"


for _echo in (False, True):
    query("pagerank" + "_echo" * _echo, _rank_sql(_echo))(lambda s, d, e=_echo: rounded(propagate.pagerank(T.trade(s, d), echo=e), 1, 9))


@query("radius_steps", O.graph("turns", HALF) + ", v0 as (select distinct src as node, 1.0::double as b from edges)" + "".join(f", v{i} as materialized (select e.src as node, sum(w * b) as b from edges e join v{i - 1} v on v.node = e.dst group by e.src)" for i in range(1, 9)) + " select round(sqrt(sqrt(sum(v8.b * v8.b)) / (select sqrt(sum(b * b)) from v6)), 6) as radius from v8")
def radius_steps(spark, d):
    return spark.createDataFrame([(round(propagate.spectral_radius(T.turns(spark, d), 8, 0.0), 6),)], "radius double")


# two-step ratios from hashed residual rows, as in the engine
_H = ", h0 as (select node, " + ", ".join(f"{O.u(f'node || {chr(39)}:{c}{chr(39)}')} / 4294967296.0 as b{c}" for c in range(3)) + " from (select distinct src as node from edges)), x as (select node, " + ", ".join(f"b{c} - (b0 + b1 + b2) / 3 as b{c}" for c in range(3)) + " from h0)"
query("radius_echo", O.graph("turns", HALF) + O.scaled(0.0, 0.0, 0.5) + _H + O.iterate(center(K3), 0.3, 8, True, keep=None) + " select round(sqrt(sqrt(sum(s8.b0 * s8.b0 + s8.b1 * s8.b1 + s8.b2 * s8.b2)) / (select sqrt(sum(b0 * b0 + b1 * b1 + b2 * b2)) from s6)), 6) as radius from s8")(
    lambda s, d: s.createDataFrame([(round(propagate.operator_radius(propagate.operator(*turns(s, d)[::2], 0.0, 0.0, 0.5), K3, 0.3, rounds=8, tol=0.0), 6),)], "radius double")
)


@query("converges_echo")
def converges_echo(spark, d):
    """Limits without and with the echo term, and whether the update converges on either side of each."""
    edges, _, seeds = turns(spark, d)
    found = []
    for echo in (False, True):
        limit = propagate.stability_limit(edges, seeds, K3, echo=echo, halvings=3, rounds=8)
        found += [(echo, limit, f, propagate.converges(edges, seeds, K3, f * limit, echo=echo, rounds=12)) for f in (0.7, 1.3)]
    return spark.createDataFrame(found, "echo boolean, eps_star double, share double, converges boolean")


_B2 = O.graph("turns", HALF) + O.scaled(0.0, 1.0, 0.5) + O.residual(3) + O.iterate(center(K3), 0.5, 3)
query("energy_general", _B2 + " select round(sum(pow(s3.b0 - coalesce(s2.b0, 0), 2) + pow(s3.b1 - coalesce(s2.b1, 0), 2) + pow(s3.b2 - coalesce(s2.b2, 0), 2)), 6) as energy from s3 left join s2 using (node)")(
    lambda s, d: (lambda e, _, x: propagate.energy(e, propagate.propagate(e, x, K3, beta=1.0, gamma=0.5, eps=0.5, r=2), x, K3, beta=1.0, gamma=0.5, eps=0.5).select(F.round("energy", 6).alias("energy")))(*turns(s, d))
)
_L2 = O.graph("turns", HALF) + O.scaled(0, 0) + O.residual(3) + O.iterate(center(K3), 0.05, 3, True)
query("energy_linear", _L2 + " select round(sum(pow(s3.b0 - coalesce(s2.b0, 0), 2) + pow(s3.b1 - coalesce(s2.b1, 0), 2) + pow(s3.b2 - coalesce(s2.b2, 0), 2)), 9) as energy from s3 left join s2 using (node)")(
    lambda s, d: (lambda e, _, x: propagate.energy(e, propagate.propagate(e, x, K3, eps=0.05, r=2, echo=True), x, K3, eps=0.05, echo=True).select(F.round("energy", 9).alias("energy")))(*turns(s, d))
)
_M = ", ".join(f"{e} as m{i}" for i, e in enumerate(O.linear(center(K3))))
query("energy_smooth", O.graph("turns", HALF) + O.scaled(1.0, 0.0) + O.residual(3) + O.iterate(center(K3), 0.5, 2) + f", m as (select node, {_M} from s2), f as (select sum(pow(s2.b0 - coalesce(x.b0, 0), 2) + pow(s2.b1 - coalesce(x.b1, 0), 2) + pow(s2.b2 - coalesce(x.b2, 0), 2)) as f from s2 left join x using (node)), g as (select sum(e.w * (pow(a.b0 - m.m0, 2) + pow(a.b1 - m.m1, 2) + pow(a.b2 - m.m2, 2))) as g from edges e join s2 a on a.node = e.src join m on m.node = e.dst) select round(f + 0.5 * g, 6) as energy from f, g")(
    lambda s, d: (lambda e, _, x: propagate.smooth_energy(e, propagate.propagate(e, x, K3, alpha=1.0, eps=0.5, r=2), x, K3).select(F.round("energy", 6).alias("energy")))(*turns(s, d))
)

# --- counts and estimators
query("nbr_counts_trade", O.graph("trade", HALF) + O.hops(5, 1) + " select * from n1")(lambda s, d: walks.neighbor_counts(*trade(s, d)[::2], 5))
for _l in (1, 2, 3, 4):
    query(f"nb_counts_l{_l}_turns", O.graph("turns", HALF) + O.hops(3, _l) + " " + O.pairs(3, f"n{_l}"))(lambda s, d, l=_l: (lambda e, _, x: walks.pair_counts(walks.hop_counts(e, x, 3, l)[-1], x, 3))(*turns(s, d)))
    query(f"nb_counts_l{_l}_trade", O.graph("trade", HALF) + O.hops(5, _l) + " " + O.pairs(5, f"n{_l}"))(lambda s, d, l=_l: (lambda e, _, x: walks.pair_counts(walks.hop_counts(e, x, 5, l)[-1], x, 5))(*trade(s, d)))
    if _l in (2, 3):
        query(f"all_counts_l{_l}_trade", O.graph("trade", HALF) + O.hops(5, _l, True) + " " + O.pairs(5, f"n{_l}"))(lambda s, d, l=_l: (lambda e, _, x: walks.pair_counts(walks.hop_counts(e, x, 5, l, True)[-1], x, 5))(*trade(s, d)))
        query(f"path_matrix_l{_l}_turns", O.graph("turns") + " select a.src, " + ("b.dst" if _l == 2 else "c.dst") + ", count(*) as n from edges a join edges b on a.dst = b.src" + (" join edges c on b.dst = c.src" if _l == 3 else "") + " group by all")(lambda s, d, l=_l: walks.path_matrix(T.turns(s, d), l))
        _walk = "select a.src, " + ("b.dst" if _l == 2 else "c.dst") + ", count(*) as n from edges a join edges b on a.dst = b.src and b.dst <> a.src" + (" join edges c on b.dst = c.src and c.dst <> b.src" if _l == 3 else "") + " group by all"
        query(f"nb_matrix_l{_l}_turns", O.graph("turns") + " " + _walk)(lambda s, d, l=_l: walks.nb_path_matrix(T.turns(s, d), l))
        query(f"walks_brute_l{_l}_turns", O.graph("turns") + " " + _walk)(lambda s, d, l=_l: walks.enumerate_walks(T.turns(s, d), l))
_COUNTS = O.graph("turns", HALF) + O.hops(3, 1) + ", m as (" + O.pairs(3, "n1") + ")"
_NORM = {
    1: "select c, d, case when sum(cnt) over (partition by c) > 0 then cnt / sum(cnt) over (partition by c) else 1 / 3.0 end as t from m",
    2: "select c, d, case when sum(cnt) over (partition by c) = 0 then 1 / 3.0 else cnt / sqrt((case when sum(cnt) over (partition by c) > 0 then sum(cnt) over (partition by c) else 1 end) * (case when sum(cnt) over (partition by d) > 0 then sum(cnt) over (partition by d) else 1 end)::double) end as t from m",
    3: "select c, d, 3.0 * cnt / (select sum(cnt) from m) as t from m",
}


def matrix(spark, M: np.ndarray, value: str) -> DataFrame:
    return spark.createDataFrame([(c, d, round(float(M[c, d]), 6) + 0.0) for c in range(len(M)) for d in range(len(M))], f"c int, d int, {value} double")


for _v in (1, 2, 3):
    query(f"normalize_{_v}", _COUNTS + f", t as ({_NORM[_v]}) select c, d, round(t, 6) + 0.0 as t from t")(lambda s, d, v=_v: matrix(s, estimate.normalize_counts(walks.count_matrices(*turns(s, d)[::2], 3, 1)[0], v), "t"))
    query(f"onehop_{_v}", _COUNTS + f", t as ({_NORM[_v]}), y as (select a.c, a.d, (a.t + b.t) / 2 as s from t a join t b on a.c = b.d and a.d = b.c), rho as (select c, 1 - sum(s) as rho from y group by c), u as (select c, (rho - (select sum(rho) from rho) / 6) / 3 as u from rho) select y.c, y.d, round(s + a.u + b.u, 6) + 0.0 as v from y join u a on a.c = y.c join u b on b.c = y.d")(
        lambda s, d, v=_v: matrix(s, estimate.estimate_onehop(*turns(s, d)[::2], 3, v), "v")
    )
query("verify_compat_turns", O.graph("turns") + O.hops(3, 1) + ", m as (" + O.pairs(3, "n1") + f"), t as ({_NORM[1]}) select c, d, round(t, 6) + 0.0 as v from t")(lambda s, d: matrix(s, estimate.normalize_counts(walks.count_matrices(T.turns(s, d), T.turn_labels(s, d), 3, 1)[0], 1), "v"))
_nn = ", ".join([f"round(sum(n.b{c} * n.b{d}), 6) + 0.0 as nn_{c}{d}" for c in range(3) for d in range(3)] + [f"round(sum(n.b{c} * coalesce((s.cls = {d})::int, 0)), 6) + 0.0 as nx_{c}{d}" for c in range(3) for d in range(3)])
query("energyfit_moments", O.graph("turns", HALF) + O.scaled(1.0, 0.0) + ", n as (select p.src as node, " + ", ".join(f"sum(p.w * (s.cls = {c})::int) as b{c}" for c in range(3)) + f" from p join seeds s on s.node = p.dst group by p.src) select {_nn} from n left join seeds s using (node)")(
    lambda s, d: (lambda m: m.select(*[(F.round(c, 6) + 0.0).alias(c) for c in m.columns]))(estimate.energy_moments(*turns(s, d)[::2], 3, alpha=1.0))
)
_MOMENTS = "with " + SQL["energyfit_moments"].split("with ", 1)[1].rsplit(" select round(", 1)[0] + ", mo as (select " + ", ".join([f"sum(n.b{c} * n.b{d}) as nn_{c}{d}" for c in range(3) for d in range(3)] + [f"sum(n.b{c} * coalesce((s.cls = {d})::int, 0)) as nx_{c}{d}" for c in range(3) for d in range(3)]) + " from n left join seeds s using (node))"
_CELLS = {(0, 0): "a", (0, 1): "b", (0, 2): "1 - a - b", (1, 1): "e", (1, 2): "1 - b - e", (2, 2): "a + 2 * b + e - 1"}
_SOLVED = lambda less, moments=_MOMENTS: moments + O.energy_solved("mo") + " " + " union all ".join(f"select {c} as c, {d} as d, round({_CELLS[min(c, d), max(c, d)]} - {less}, 6) + 0.0 as v from h" for c in range(3) for d in range(3))
for _name, _mode, _less in (("solve", "free", "0"), ("constrained", "constrained", "0"), ("residual", "residual", "1 / 3.0")):
    query(f"energyfit_{_name}", _SOLVED(_less))(lambda s, d, m=_mode: matrix(s, estimate.estimate_energy(*turns(s, d)[::2], 3, alpha=1.0, mode=m), "v"))
query("energyfit_labelled", _SOLVED("0", _MOMENTS.replace("from n left join seeds", "from n join seeds")))(lambda s, d: matrix(s, estimate.estimate_energy(*turns(s, d)[::2], 3, alpha=1.0, rows="labelled"), "v"))
query("onehop_residual", _COUNTS + f", t as ({_NORM[1]})" + O.projected("t") + " select c, d, round(v - 1 / 3.0, 6) + 0.0 as v from v")(lambda s, d: matrix(s, estimate.estimate_onehop(*turns(s, d)[::2], 3, residual=True), "v"))
query("multihop_residual")(lambda s, d: matrix(s, estimate.estimate_multihop(*turns(s, d)[::2], 3, residual=True), "v"))
query("pairs_per_hop", O.graph("turns", HALF) + O.hops(3, 4) + " select l::int as hop, n from (" + " union all ".join(f"select {l} as l, (select coalesce(sum(cnt), 0)::bigint from ({O.pairs(3, f'n{l}')})) as n" for l in (1, 2, 3, 4)) + ")")(
    lambda s, d: s.createDataFrame([(l + 1, n) for l, n in enumerate(walks.pairs_available(*turns(s, d)[::2], 3, 4))], "hop int, n long")
)


@query("estimate_report")
def estimate_report(spark, d):
    """What a five-hop estimate on turns rests on."""
    r = estimate.estimate_report(*turns(spark, d)[::2], 3)
    return spark.createDataFrame([(l + 1, n, e) for l, (n, e) in enumerate(zip(r.pairs, r.empty_rows, strict=True))], "hop int, pairs long, empty_rows array<int>")


query("multihop_fit")(lambda s, d: matrix(s, estimate.estimate_multihop(*turns(s, d)[::2], 3), "v"))
query("bp_turns", O.graph("turns", HALF) + O.beliefs_of_messages(K3, 4) + f" select {O.rounded(3)} from bel")(lambda s, d: rounded(propagate.belief_propagation(*turns(s, d)[::2], K3), 3))

# --- predictions and measures
_PRED = ", pred as (select node, case when round(b0, 9) >= round(greatest(b1, b2), 9) then 0 when round(b1, 9) >= round(b2, 9) then 1 else 2 end as cls from s4), hidden as (select l.node, l.cls as truth, coalesce(p.cls, -1) as cls from labels l left join pred p using (node) where l.node not in (select node from seeds))"
_REC = O.graph("turns", HALF) + O.scaled(0.0, 1.0, 0.5) + O.residual(3) + O.iterate(center(K3), 0.5, 4) + _PRED


def held(spark, d):
    edges, labels, seeds = turns(spark, d)
    return L.hold_out(L.predict(propagate.member("recommended", edges, seeds, K3, eps=0.5, r=4), 3), labels, seeds)


query("holdout_turns", _REC + " select count(*) as hidden, sum((truth = cls)::bigint)::bigint as correct, sum((cls < 0)::bigint)::bigint as unreached from hidden")(lambda s, d: L.accuracy(held(s, d)))
query("confusion", _REC + " select truth, cls, count(*) as n from hidden group by all")(lambda s, d: L.confusion(held(s, d)))
query("accuracy_by_class", _REC + " select truth, count(*) as n, round(avg((truth = cls)::int), 6) as recall from hidden group by truth")(lambda s, d: held(s, d).groupBy("truth").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("truth") == F.col("cls")).cast("int")), 6).alias("recall")))
_PER = _REC + ", k as (select unnest([0, 1, 2])::int as c), g as (select c, sum((truth = c and cls = c)::int) as hit, sum((truth = c)::int) as t, sum((cls = c)::int) as s from hidden, k group by c)"
query("per_class", _PER + " select c as cls, round(case when s > 0 then hit / s end, 6) as precision, round(case when t > 0 then hit / t end, 6) as recall, round(case when s + t > 0 then 2 * hit / (s + t) end, 6) as f1 from g")(
    lambda s, d: L.per_class(held(s, d), 3).select("cls", *[F.round(c, 6).alias(c) for c in ("precision", "recall", "f1")])
)
query("macro_accuracy", _PER + " select round(avg(case when t > 0 then hit / t end), 6) as macro from g")(lambda s, d: L.macro_accuracy(held(s, d), 3).select(F.round("macro", 6).alias("macro")))
query("random_guess", O.graph("turns", HALF) + f" select count(*) as hidden, sum(({O.u('node')} % 3 = cls)::bigint)::bigint as correct, sum((cls < 0)::bigint)::bigint as unreached from labels where node not in (select node from seeds)")(
    lambda s, d: (lambda e, lab, x: L.accuracy(L.hold_out(L.random_guess(lab, 3), lab, x)))(*turns(s, d))
)
query("top_conf", _REC + ", g as (select node, cls, greatest(b0, b1, b2) as top from s4 join pred using (node)) select node, cls, pos from (select node, cls, row_number() over (partition by cls order by round(top, 6) desc, node) as pos from g) where pos <= 5")(
    lambda s, d: (lambda b: b.join(L.predict(b, 3), "node").withColumn("pos", F.row_number().over(W.partitionBy("cls").orderBy(F.desc(F.round(F.greatest("b0", "b1", "b2"), 6)), "node"))).filter("pos <= 5").select("node", "cls", "pos"))(propagate.member("recommended", *turns(s, d)[::2], K3, eps=0.5, r=4))
)
query("set_label_change", O.graph("turns", HALF) + O.scaled(0.0, 1.0, 0.5) + O.residual(3) + O.iterate(center(K3), 0.5, 4) + ", a as (select node, case when round(b0, 9) >= round(greatest(b1, b2), 9) then 0 when round(b1, 9) >= round(b2, 9) then 1 else 2 end as cls from s3), b as (select node, case when round(b0, 9) >= round(greatest(b1, b2), 9) then 0 when round(b1, 9) >= round(b2, 9) then 1 else 2 end as cls from s4) select * from b except select * from a")(
    lambda s, d: (lambda e, _, x: L.predict(propagate.member("recommended", e, x, K3, eps=0.5, r=4), 3).select("node", "cls").exceptAll(L.predict(propagate.member("recommended", e, x, K3, eps=0.5, r=3), 3).select("node", "cls")))(*turns(s, d))
)
query("l2_turns", _COUNTS + f", t as ({_NORM[1]}), k(c, d, v) as (values " + ", ".join(f"({c}, {x}, {float(K3[c, x])!r})" for c in range(3) for x in range(3)) + ") select round(sqrt(sum(pow(t - v, 2))), 6) as l2 from t join k using (c, d)")(
    lambda s, d: s.createDataFrame([(round(float(np.linalg.norm(estimate.normalize_counts(walks.count_matrices(*turns(s, d)[::2], 3, 1)[0], 1) - K3)), 6),)], "l2 double")
)
query("path_nnz", O.graph("turns") + " select count(*) as edges, (select count(*) from (select distinct a.src, b.dst from edges a join edges b on a.dst = b.src)) as two_hop from edges")(lambda s, d: (lambda e: e.agg(F.count(F.lit(1)).alias("edges")).crossJoin(walks.path_matrix(e, 2).agg(F.count(F.lit(1)).alias("two_hop"))))(T.turns(s, d)))
_RUNS = ", ".join(f"h{i} as (select avg(({O.u(f"'{i}:' || node")} % 3 = cls)::int) as a from labels)" for i in range(3))


@query("accuracy_stats", f"with {O.LABELS['turns']}, {_RUNS}, r as (select a from h0 union all select a from h1 union all select a from h2) select round(avg(a), 6) as mean, round(stddev_samp(a), 6) as std, round(stddev_samp(a) / sqrt(3), 6) as error from r")
def accuracy_stats(spark, d):
    """Mean, deviation and standard error of three random labellings."""
    labels, runs = T.turn_labels(spark, d), None
    for i in range(3):
        own = L.accuracy(L.hold_out(L.random_guess(labels, 3, i), labels, labels.limit(0))).select((F.col("correct") / F.col("hidden")).alias("accuracy"))
        runs = own if runs is None else runs.unionByName(own)
    return L.accuracy_stats(runs).select(*[F.round(c, 6).alias(c) for c in ("mean", "std", "error")])


_SETTLE = O.graph("turns", HALF) + O.scaled(0.0, 1.0, 0.5) + O.residual(3) + O.iterate(center(K3), 0.5, 4) + O.predicted("x", "l0") + "".join(O.predicted(f"s{i}", f"l{i}") for i in range(1, 5))
query("settle_steps", _SETTLE + " " + " union all ".join(f"select {i} as r, count(*) filter (a.cls is null or a.cls <> b.cls) as changed from l{i} b left join l{i - 1} a using (node)" for i in range(1, 5)))(lambda s, d: propagate.settle_steps(*turns(s, d)[::2], K3, 4, beta=1.0, gamma=0.5, eps=0.5))

# --- planted graphs
_N = "n as (select count(*) as n from customer), cl as (select c_custkey as node, ((row_number() over (order by ('0x' || substr(md5('1:' || c_custkey), 1, 8))::bigint, c_custkey) - 1)) as r0 from customer), sz as (select c, n // 3 + (c < n % 3)::int as s from n, range(3) t(c)), bd as (select c, sum(s) over (order by c) as upto from sz), classes as (select node, (select min(c) from bd where r0 < upto)::int as cls from cl)"
keys = lambda s, d: T.table(s, d, "customer", "c_custkey").select(F.col("c_custkey").alias("node"))
query("planted_classes", "with " + _N + " select * from classes")(lambda s, d: planted.assign_classes(keys(s, d), [1 / 3] * 3))
query("planted_degrees", "with " + _N + ", rk as (select node, cls, row_number() over (partition by cls order by ('0x' || substr(md5('d1:' || node), 1, 8))::bigint, node) as r from classes), ex as (select *, round(5000 * pow(r, -0.3) / sum(pow(r, -0.3)) over (partition by cls), 9) as e from rk), q as (select *, row_number() over (partition by cls order by greatest(4294967295 - floor((e - floor(e)) * 4294967296.0)::bigint, 0), r) as q, 5000 - sum(floor(e)::bigint) over (partition by cls) as rest from ex) select node, cls, (floor(e)::bigint + (q <= rest)::bigint) as d from q")(
    lambda s, d: planted.assign_degrees(planted.assign_classes(keys(s, d), [1 / 3] * 3), [5000] * 3)
)


_K3 = ", ".join(f"({c}, {d}, {float(K3[c, d])!r}::double)" for c in range(3) for d in range(3))
_BUDGET = f"with n as (select count(*) * 5 as m from customer), k(c, d, v) as (values {_K3}), x as (select c, d, m * v / (select sum(v) from k) as exact from k, n), f as (select *, floor(exact + 1e-9)::bigint as low from x), bd as (select c, d, low + (row_number() over (order by round(low - exact, 6), least(c, d), greatest(c, d), c, d) <= (select m from n) - sum(low) over ())::bigint as n from f)"


@query("planted_budget", _BUDGET + " select c, d, n from bd")
def planted_budget(spark, d):
    """Arcs of each class pair for a mean degree of 10 over the customers."""
    n = keys(spark, d).agg(F.count("node") + F.count_if(F.col("node").isNull())).first()[0]  # of the keys themselves, not of the files' footers
    M = planted.edge_budget(n * 5, K3)
    return spark.createDataFrame([(c, x, int(M[c, x])) for c in range(3) for x in range(3)], "c int, d int, n long")


def graph9(spark, d, degree=10):
    return planted.planted_graph(keys(spark, d), K3, degree)


query("planted_edges")(lambda s, d: graph9(s, d)[0])


query("planted_check", _BUDGET + " select a.c, a.d, a.n + b.n as n from bd a join bd b on a.c = b.d and a.d = b.c")(lambda s, d: planted.planted_check(*graph9(s, d)[:2]))


@query("planted_labelled")
def planted_labelled(spark, d):
    """Generate, hide, estimate over several hops, propagate, predict."""
    edges, labels, _ = graph9(spark, d, 10)
    seeds = L.hide_labels(labels, 0.1)
    return estimate.label_graph(edges, seeds, 3)


_ROWS = K3 / K3.sum(1, keepdims=True)
_DRAW = "case " + " ".join(f"when s.cls = {c} then case when u < {float(np.cumsum(_ROWS[c])[0])!r} then 0 when u < {float(np.cumsum(_ROWS[c])[1])!r} then 1 else 2 end" for c in range(3)) + " end"
query(
    "block_model",
    "with " + _N + f", num as (select node, cls, row_number() over (partition by cls order by {O.u("'b1:' || node")}, node) as r, count(*) over (partition by cls) as size from classes)"
    + f", st as (select node, cls, {O.u("'x1:' || node || ':' || i")} / 4294967296.0 as u, {O.u("'y1:' || node || ':' || i")} / 4294967296.0 as v from classes, range(1, 6) t(i))"
    + f", dr as (select s.node, s.v, {_DRAW} as d from st s), sz2 as (select cls, any_value(size) as size from num group by cls)"
    + " select distinct dr.node as src, num.node as dst, 1.0::double as w from dr join sz2 on sz2.cls = dr.d join num on num.cls = dr.d and num.r = floor(dr.v * sz2.size)::bigint + 1 where dr.node <> num.node",
)(lambda s, d: planted.block_model(keys(s, d), planted.assign_classes(keys(s, d), [1 / 3] * 3), K3, 10))
query("degree_hist", O.graph("copart") + ", g as (select src, count(*) as deg from edges group by src) select deg, count(*) as n from g group by deg")(lambda s, d: planted.degree_histogram(T.copart(s, d)))
query("clustered_adjacency", O.graph("turns") + f", o as (select node, ((row_number() over (order by cls, {O.u("'o:' || node")}, node) - 1) // 100)::int as bin from labels) select x.bin as row_bin, y.bin as col_bin, count(*) as n from edges e join o x on x.node = e.src join o y on y.node = e.dst group by all")(lambda s, d: planted.clustered_adjacency(T.turns(s, d), T.turn_labels(s, d), 100))
query("coloring_conflicts", O.graph("tree") + ", l as (select distinct src as node, least(src % 4, 2) as cls from edges), r as (select node, (node // 4) % 2 as cls from l) select (select count(*) from edges e join l a on a.node = e.src join l b on b.node = e.dst where e.src < e.dst and a.cls = b.cls) as by_level, (select count(*) from edges e join r a on a.node = e.src join r b on b.node = e.dst where e.src < e.dst and a.cls = b.cls) as by_parity")(
    lambda s, d: (lambda e, n: planted.coloring_conflicts(e, n.select("node", F.least(F.col("node") % 4, F.lit(2)).alias("cls"))).toDF("by_level").crossJoin(planted.coloring_conflicts(e, n.select("node", (F.floor(F.col("node") / 4) % 2).alias("cls"))).toDF("by_parity")))(T.tree(s, d), T.tree(s, d).select(F.col("src").alias("node")).distinct())  # one row each
)


@query("planted_source")
def planted_graph_source(spark, d):
    """Arcs between the customers, drawn by the Python data source: its node i is the customer of place i in a hashed order."""
    planted_source.register(spark)
    c = keys(spark, d).select("node", planted.hashed(1, F.col("node")).alias("u"), F.lit(0).alias("g"))
    placed = planted.ranked(c, ["g"], "u", ["node"], "r").select("node", (F.col("r") - 1).alias("i"))
    arcs = spark.read.format("planted").options(nodes=keys(spark, d).count(), degree=10, partitions=4).load().toDF("x", "y")
    return arcs.join(placed.toDF("src", "x"), "x").join(placed.toDF("dst", "y"), "y").select("src", "dst")


# --- general operators a user of the methods needs
_RT = O.graph("turns") + ", pc as (select a.cls as c, b.cls as d from edges e join labels a on a.node = e.src join labels b on b.node = e.dst)"


def class_pairs(spark, d):
    e, lab, _ = turns(spark, d, None)
    return e.join(lab.select(F.col("node").alias("src"), F.col("cls").alias("c")), "src").join(lab.select(F.col("node").alias("dst"), F.col("cls").alias("d")), "dst")


query("pair_counts_turns", _RT + " select c, d, count(*) as cnt from pc group by all")(lambda s, d: class_pairs(s, d).groupBy("c", "d").agg(F.count(F.lit(1)).alias("cnt")))
query("cube_pairs", _RT + " select c, d, count(*) as n from pc group by cube (c, d)")(lambda s, d: class_pairs(s, d).cube("c", "d").agg(F.count(F.lit(1)).alias("n")))
query("rollup_pairs", _RT + " select c, d, count(*) as n from pc group by rollup (c, d)")(lambda s, d: class_pairs(s, d).rollup("c", "d").agg(F.count(F.lit(1)).alias("n")))
query("grouping_sets_pairs", _RT + " select c, d, count(*) as n from pc group by grouping sets ((c), (d), ())")(lambda s, d: class_pairs(s, d).groupingSets([["c"], ["d"], []], "c", "d").agg(F.count(F.lit(1)).alias("n")))
query("scalar_subquery_norm", _RT + " select c, d, round(count(*) * 3.0 / (select count(*) from pc), 6) as t from pc group by all")(lambda s, d: (lambda p: p.groupBy("c", "d").agg(F.count(F.lit(1)).alias("n")).select("c", "d", F.round(F.col("n") * 3.0 / F.sum("n").over(W.partitionBy(F.lit(1))), 6).alias("t")))(class_pairs(s, d)))
query("class_dict", "select (row_number() over (order by t) - 1)::int as cls, t as name from (select distinct event_type as t from events)")(lambda s, d: T.table(s, d, "events", "event_type").distinct().select((F.row_number().over(W.orderBy("event_type")) - 1).cast("int").alias("cls"), F.col("event_type").alias("name")))
query("bipartite_pack", "select 2 * c_custkey as node, 'c' as side from customer union all select 2 * s_suppkey + 1, 's' from supplier")(lambda s, d: T.table(s, d, "customer", "c_custkey").select((2 * F.col("c_custkey")).alias("node"), F.lit("c").alias("side")).unionByName(T.table(s, d, "supplier", "s_suppkey").select((2 * F.col("s_suppkey") + 1).alias("node"), F.lit("s").alias("side"))))
query("induced_subgraph", O.graph("trade", HALF) + " select * from edges where src in (select node from seeds) and dst in (select node from seeds)")(lambda s, d: (lambda e, _, x: e.join(x.select(F.col("node").alias("src")), "src", "left_semi").join(x.select(F.col("node").alias("dst")), "dst", "left_semi"))(*trade(s, d)))
query("anti_hidden", O.graph("turns", HALF) + " select * from labels where node not in (select node from seeds)")(lambda s, d: (lambda e, lab, x: lab.join(x, "node", "left_anti"))(*turns(s, d)))
query("full_outer_truth", O.graph("turns", 0.3) + f", other as (select node, cls as cls2 from labels where {O.u('node')} >= {int(0.2 * 2**32)} and {O.u('node')} < {int(0.6 * 2**32)}) select node, cls, cls2 from seeds full join other using (node)")(
    lambda s, d: (lambda lab: L.hide_labels(lab, 0.3).join(lab.filter(L.uniform(F.col("node")).between(int(0.2 * 2**32), int(0.6 * 2**32) - 1)).withColumnRenamed("cls", "cls2"), "node", "full"))(T.turn_labels(s, d))
)
query("exists_labelled", O.graph("turns", HALF) + " select node from labels l where exists (select 1 from edges e join seeds s on s.node = e.dst where e.src = l.node)")(lambda s, d: (lambda e, lab, x: lab.select("node").join(e.join(x.select(F.col("node").alias("dst")), "dst", "left_semi").select(F.col("src").alias("node")), "node", "left_semi"))(*turns(s, d)))
query("distinct_reach", O.graph("turns", HALF) + " select count(distinct e.src) as reached from edges e join seeds s on s.node = e.dst")(lambda s, d: (lambda e, _, x: e.join(x.select(F.col("node").alias("dst")), "dst", "left_semi").agg(F.countDistinct("src").alias("reached")))(*turns(s, d)))
query("union_intersect_except", O.graph("turns", HALF) + " (select node from labels where cls = 0 intersect select node from seeds) union all (select node from labels where cls = 2 except select node from seeds)")(lambda s, d: (lambda e, lab, x: lab.filter("cls = 0").select("node").intersect(x.select("node")).unionAll(lab.filter("cls = 2").select("node").exceptAll(x.select("node"))))(*turns(s, d)))
query("sample_hash", O.graph("trade") + f" select src, dst, w from edges where {O.u(chr(39) + 'e' + chr(39) + ' || least(src, dst) || ' + chr(39) + ':' + chr(39) + ' || greatest(src, dst)')} < {2**30}")(lambda s, d: T.trade(s, d).filter(L.uniform(F.concat(F.lit("e"), F.least("src", "dst"), F.lit(":"), F.greatest("src", "dst"))) < 2**30))
query("unpivot_state", O.graph("turns", HALF) + O.hops(3, 1) + " select node, 0 as cls, b0 as n from n1 union all select node, 1, b1 from n1 union all select node, 2, b2 from n1")(lambda s, d: walks.neighbor_counts(*turns(s, d)[::2], 3).unpivot("node", ["b0", "b1", "b2"], "name", "n").select("node", F.substring("name", 2, 1).cast("int").alias("cls"), "n"))
query("ntile_degree", O.graph("tree") + ", g as (select src as node, count(*) as deg from edges group by src) select node, deg, ntile(4) over (partition by node % 4 order by deg, node) as quarter, rank() over (partition by node % 4 order by deg) as place from g")(
    lambda s, d: T.tree(s, d).groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("deg")).select("node", "deg", F.ntile(4).over(W.partitionBy(F.col("node") % 4).orderBy("deg", "node")).alias("quarter"), F.rank().over(W.partitionBy(F.col("node") % 4).orderBy("deg")).alias("place"))
)
query("running_budget", "select o_custkey, o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderkey rows unbounded preceding), 2) as spent from orders")(lambda s, d: T.table(s, d, "orders", "o_custkey", "o_orderkey", "o_totalprice").select("o_custkey", "o_orderkey", F.round(F.sum("o_totalprice").over(W.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(W.unboundedPreceding, 0)), 2).alias("spent")))
query("json_props_weight", "select user_id, sum(json_extract_string(props, '$.k')::bigint)::bigint as w from events group by user_id")(lambda s, d: T.table(s, d, "events", "user_id", "props").groupBy("user_id").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("w")))
query("asof_events", "select x.user_id, x.event_id, y.event_id as before from (select * from events where event_type = 'purchase') x asof left join (select * from events where event_type <> 'purchase') y on x.user_id = y.user_id and x.ts > y.ts")(
    lambda s, d: T.table(s, d, "events", "user_id", "event_id", "event_type", "ts").withColumn("before", F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))).filter("event_type = 'purchase'").select("user_id", "event_id", "before")
)
query("interval_events", "select x.event_id as a, y.event_id as b from events x join events y on x.user_id = y.user_id and y.ts > x.ts and y.ts <= x.ts + interval 1 hour")(
    lambda s, d: (lambda e: e.alias("x").join(e.alias("y"), (F.col("x.user_id") == F.col("y.user_id")) & (F.col("y.ts") > F.col("x.ts")) & (F.col("y.ts") <= F.col("x.ts") + F.expr("interval 1 hour"))).select(F.col("x.event_id").alias("a"), F.col("y.event_id").alias("b")))(T.table(s, d, "events", "user_id", "event_id", "ts"))
)
_STEPS = "st as (select * from (select ts, lag(event_type) over (partition by user_id order by ts, event_id) as a, event_type as b from events) where a is not null)"
_EV = ("event_id", "ts", "user_id", "event_type")
query("daily_pairs", "with " + _STEPS + " select date_trunc('day', ts)::timestamp as start, a, b, count(*) as n from st group by all")(lambda s, d: stream.windowed(stream.class_steps(T.table(s, d, "events", *_EV))))
query("sliding_pairs", "with " + _STEPS + ", w as (select a, b, time_bucket(interval 6 hour, ts, timestamp '1970-01-01') - interval 6 hour * i as start from st, range(4) t(i)) select start, a, b, count(*) as n from w group by all")(lambda s, d: stream.windowed(stream.class_steps(T.table(s, d, "events", *_EV)), "1 day", "6 hours"))
query("session_pairs", "with g as (select user_id, ts, (coalesce(ts - lag(ts) over w >= interval 30 minute, true))::int as new from events window w as (partition by user_id order by ts, event_id)), s as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as i from g) select user_id, min(ts) as start, count(*) as n from s group by user_id, i")(lambda s, d: stream.sessions(T.table(s, d, "events", *_EV)))


def roundtrip(spark, d, kind: str) -> DataFrame:
    """Edges of turns written in a format and read with the fixed schema."""
    import uuid

    at = shared_dir(spark) + f"/edges-{uuid.uuid4().hex}"
    out = T.turns(spark, d).write
    {"csv": lambda: out.csv(at, header=True), "tsv": lambda: out.csv(at, header=True, sep="\t"), "json": lambda: out.json(at), "orc": lambda: out.orc(at)}[kind]()
    return T.check_schema(T.read_edges(spark, at, kind))


for _kind in ("csv", "tsv", "json", "orc"):
    query(f"{_kind}_roundtrip", O.graph("turns") + " select * from edges")(lambda s, d, k=_kind: roundtrip(s, d, k))
query("link_collisions", "with l as (select distinct unnest(regexp_extract_all(html, '<a href=\"([^\"]*)\"', 1)) as h from pages), i as (select ('0x' || substr(md5(h), 1, 12))::bigint as id from l) select count(*) - count(distinct id) as collisions from i")(lambda s, d: T.collisions(T.link_ids(s, d)))
query("edges_lines", "with l as (select doc_id, unnest(list_distinct(string_split(text, chr(10)))) as line from documents), g as (select doc_id, min(doc_id) over (partition by line) as a, line from l where length(line) >= 40), raw as (select a, doc_id as b, count(*)::double as w from g where a <> doc_id group by all), edges as (select a as src, b as dst, w from raw union all select b, a, w from raw) select * from edges")(T.shared_lines)
query("page_langs", "with p as (select 2 * page_id as node, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) as lang from pages), n as (select lang, (row_number() over (order by lang) - 1)::int as cls from (select distinct lang from p where lang <> '')) select node, cls from p join n using (lang)")(T.page_labels)
query("dedup_events", "select distinct event_id, ts, user_id, event_type from events")(lambda s, d: (lambda e: stream.deduplicated(e.unionByName(e)))(T.table(s, d, "events", "event_id", "ts", "user_id", "event_type")))
query("typed_events", "with n as (select (row_number() over (order by t) - 1)::int as cls, t from (select distinct event_type as t from events)) select event_id, event_type, cls from events join n on t = event_type")(
    lambda s, d: stream.with_classes(T.table(s, d, "events", "event_id", "event_type"), QUERIES["class_dict"](s, d)).select("event_id", "event_type", "cls")
)
query("approx_reach")(lambda s, d: (lambda e, _, x: e.join(x.select(F.col("node").alias("dst")), "dst", "left_semi").agg(F.approx_count_distinct("src").alias("about"), F.countDistinct("src").alias("reached")))(*turns(s, d)))

# --- weighted walks, hubs, further energies, neighbour graphs
_b5 = lambda expr: ", ".join(f"sum({expr.format(c)}) as b{c}" for c in range(5))
_WEIGHTED = (
    O.graph("trade", HALF)
    + ", x as (select node, " + ", ".join(f"coalesce((cls = {c})::int, 0)::double as b{c}" for c in range(5)) + " from (select distinct src as node from edges) left join seeds using (node))"
    + ", d2 as (select src as node, sum(w * w) as q from edges group by src)"
    + "".join(f", a{i} as materialized (select e.src as node, {_b5('e.w * v.b{}')} from edges e join {'x' if i == 1 else f'a{i - 1}'} v on v.node = e.dst group by e.src)" for i in (1, 2, 3))
    + f", ad as (select e.src as node, {_b5('e.w * d2.q * x.b{}')} from edges e join x on x.node = e.dst join d2 on d2.node = e.dst group by e.src)"
    + f", cube as (select e.src as node, {_b5('pow(e.w, 3) * x.b{}')} from edges e join x on x.node = e.dst group by e.src)"
    + ", n3 as (select node, " + ", ".join(f"a3.b{c} - d2.q * a1.b{c} - ad.b{c} + cube.b{c} as b{c}" for c in range(5)) + " from a3 join a1 using (node) join d2 using (node) join ad using (node) join cube using (node))"
    + ", n2 as (select node, " + ", ".join(f"a2.b{c} - d2.q * x.b{c} as b{c}" for c in range(5)) + " from a2 join d2 using (node) join x using (node))"
)
for _l in (2, 3):
    query(f"weighted_counts_l{_l}_trade", _WEIGHTED + f" select cls as c, {_b5('b{}')} from n{_l} join seeds using (node) group by cls")(
        lambda s, d, l=_l: (lambda e, _, x: x.join(walks.weighted_hop_counts(e, x, 5, l)[-1], "node").groupBy(F.col("cls").alias("c")).agg(*[F.sum(b).alias(b) for b in L.names(5)]))(*trade(s, d))
    )
query("prop_trade_hubs", SQL["prop_trade_col"])(lambda s, d: rounded(propagate.propagate(*trade(s, d)[::2], K5, beta=1.0, gamma=0.5, eps=0.5, r=3, hub_edges=50), 5))
_S2 = O.graph("turns", HALF) + O.scaled(1.0, 0.0) + O.residual(3) + O.iterate(center(K3), 0.5, 2) + ", dg as (select src as node, sum(w) as deg from edges group by src), m as (select node, " + ", ".join(f"{e} as m{i}" for i, e in enumerate(O.linear(K3))) + " from s2)"
_DOT = " + ".join(f"s2.b{c} * m.m{c}" for c in range(3))


def _beliefs(spark, d):
    edges, _, seeds = turns(spark, d)
    return edges, propagate.propagate(edges, seeds, K3, alpha=1.0, eps=0.5, r=2)


for _kind, _own, _across in (("laplacian", "dg.deg", "e.w"), ("normalised", "1", "e.w / sqrt(x.deg * y.deg)")):
    query(f"energy_modulated_{_kind}", _S2 + f" select round((select sum({_own} * ({_DOT})) from s2 join m using (node) join dg using (node)) - (select sum({_across} * ({_DOT})) from edges e join s2 on s2.node = e.src join m on m.node = e.dst join dg x on x.node = e.src join dg y on y.node = e.dst), 6) as energy")(
        lambda s, d, n=_kind == "normalised": propagate.smoothness(*_beliefs(s, d), K3, n).select(F.round("energy", 6).alias("energy"))
    )
query("energy_reconstruct", _S2 + ", t as (select e.src as node, " + ", ".join(f"sum(e.w / dg.deg * s2.b{c}) as t{c}" for c in range(3)) + " from edges e join s2 on s2.node = e.dst join dg on dg.node = e.src group by e.src) select round(sum(" + " + ".join(f"pow(coalesce(b{c}, 0) - coalesce(t{c}, 0), 2)" for c in range(3)) + "), 6) as energy from s2 full join t using (node)")(
    lambda s, d: propagate.reconstruction_energy(*_beliefs(s, d), 3).select(F.round("energy", 6).alias("energy"))
)
_NEAR = "with v as (select vec_id, embedding::double[] as e from embeddings), c as (select x.vec_id as a, y.vec_id as b, round(list_dot_product(x.e, y.e) / sqrt(list_dot_product(x.e, x.e) * list_dot_product(y.e, y.e)), 6) as cos from v x, v y where x.vec_id <> y.vec_id), t as (select *, (row_number() over (partition by a order by cos desc, b))::int as pos from c qualify pos <= 5)"
query("cosine_pairs", _NEAR + " select a, b, cos, pos from t")(lambda s, d: T.nearest(T.table(s, d, "embeddings", "vec_id", "embedding")))
query("edges_knn", _NEAR + ", u as (select distinct least(a, b) as a, greatest(a, b) as b from t) select a as src, b as dst, 1.0::double as w from u union all select b, a, 1.0 from u")(lambda s, d: T.knn(s, d))
query("knn_hashed")(lambda s, d: T.knn(s, d, bits=3, tables=12))
query("pair_counts_docs", O.graph("docs") + " select x.quality as c, y.quality as d, count(*) as cnt from edges e join labels x on x.doc_id = e.src join labels y on y.doc_id = e.dst group by all")(
    lambda s, d: (lambda q: T.same_text(s, d).join(q.toDF("src", "c"), "src").join(q.toDF("dst", "d"), "dst").groupBy("c", "d").agg(F.count(F.lit(1)).alias("cnt")))(T.table(s, d, "labels", "doc_id", "quality"))
)
query("walks_brute_l3_tree", O.graph("tree") + " select a.src, c.dst, count(*) as n from edges a join edges b on a.dst = b.src and b.dst <> a.src join edges c on b.dst = c.src and c.dst <> b.src group by all")(lambda s, d: walks.enumerate_walks(T.tree(s, d), 3))
# a root's belief p reaches depth l of its tree as p K^l: halved distance from 1/5 a level
query(
    "bp_tree",
    "with recursive "
    + O.EDGES["tree"]
    + ", t as (select distinct 4 * n_regionkey::bigint as node, n_regionkey::int as cls, 0 as l from nation union all select raw.b, t.cls, t.l + 1 from t join raw on raw.a = t.node) select node, "
    + ", ".join(f"round(0.2 + (case when cls = {c} then 0.7 else -0.175 end) * pow(0.5, l), 6) as b{c}" for c in range(5))
    + " from t",
)(lambda s, d: rounded(propagate.belief_propagation(T.tree(s, d), T.table(s, d, "region", "r_regionkey").select((4 * F.col("r_regionkey")).cast("long").alias("node"), F.col("r_regionkey").cast("int").alias("cls")), K5, r=4), 5))


_NATIONS = "with raw as (select least(c_nationkey, s_nationkey)::bigint as a, greatest(c_nationkey, s_nationkey)::bigint as b, count(*)::double as w from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey where c_nationkey <> s_nationkey group by all), " + O.BOTH + ", seeds as (select n_nationkey::bigint as node, n_regionkey::int as cls from nation where n_nationkey % 2 = 0)"


@query("closed_form_micro", _NATIONS + O.scaled(0.5, 0.5) + O.residual(5) + O.iterate(center(K5), 0.1, 16) + f" select {O.rounded(5)} from s16")
def closed_form_micro(spark, d):
    """The fixed point of the trade between nations (25 nodes, by lines of orders), solved densely; the SQL iterates until nothing moves."""
    o, l = T.table(spark, d, "orders", "o_orderkey", "o_custkey"), T.table(spark, d, "lineitem", "l_orderkey", "l_suppkey")
    c, s = T.table(spark, d, "customer", "c_custkey", "c_nationkey"), T.table(spark, d, "supplier", "s_suppkey", "s_nationkey")
    lines = l.join(o, l.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(s, l.l_suppkey == s.s_suppkey)
    edges = T.normalise_edges(lines.select(F.col("c_nationkey").cast("long").alias("a"), F.col("s_nationkey").cast("long").alias("b"), F.lit(1.0).alias("w"))).persist()
    seeds = T.table(spark, d, "nation", "n_nationkey", "n_regionkey").filter("n_nationkey % 2 = 0").select(F.col("n_nationkey").cast("long").alias("node"), F.col("n_regionkey").cast("int").alias("cls"))
    found = propagate.closed_form(edges, seeds, K5, alpha=0.5, beta=0.5)
    edges.unpersist()
    return rounded(spark.createDataFrame([(int(n), *map(float, b)) for n, b in found.items()], "node long, b0 double, b1 double, b2 double, b3 double, b4 double"), 5)


query("semi_seeds", O.graph("trade", HALF) + " select * from edges where dst in (select node from seeds)")(lambda s, d: (lambda e, _, x: e.join(x.select(F.col("node").alias("dst")), "dst", "left_semi").select("src", "dst", "w"))(*trade(s, d)))


@query("cross_modulate", SQL["modulate_turns"])
def cross_modulate(spark, d):
    """The modulated rows by a join with K as a table of k x k rows."""
    x = L.residual(turns(spark, d)[2], 3).unpivot("node", ["b0", "b1", "b2"], "name", "b").withColumn("c", F.substring("name", 2, 1).cast("int"))
    K = spark.createDataFrame([(c, e, float(K3[c, e])) for c in range(3) for e in range(3)], "c int, d int, v double")
    return rounded(x.join(F.broadcast(K), "c").groupBy("node").pivot("d", [0, 1, 2]).agg(F.sum(F.col("b") * F.col("v"))).toDF("node", "b0", "b1", "b2"), 3)


_MARGIN = "round(greatest(b0, b1, b2) - (b0 + b1 + b2 - greatest(b0, b1, b2) - least(b0, b1, b2)), 6)"
query("topk_margin", _REC + f" select node, {_MARGIN} as margin from s4 order by margin desc, node limit 20")(lambda s, d: (lambda e, _, x: propagate.member("recommended", e, x, K3, eps=0.5, r=4).select("node", F.expr(_MARGIN).alias("margin")).orderBy(F.desc("margin"), "node").limit(20))(*turns(s, d)))


_DAYS = (
    "with " + _STEPS + ", n as (select t, (row_number() over (order by t) - 1)::int as i from (select distinct event_type as t from events)), w as (select date_trunc('day', ts)::timestamp as start, a, b, count(*) as n from st group by all)"
    ", one as (select start, x.i as c, y.i as d, n from w join n x on x.t = a join n y on y.t = b), cells as (select start, c, d, n from one union all select start, d, c, n from one), grid as (select start, x.i as c, y.i as d from (select distinct start from w), n x, n y)"
    ", m as (select g.start, g.c, g.d, coalesce(sum(n), 0) as cnt from grid g left join cells e on e.start = g.start and e.c = g.c and e.d = g.d group by all)"
    ", t as (select start, c, d, case when sum(cnt) over (partition by start, c) > 0 then cnt / sum(cnt) over (partition by start, c) else 0.2 end as t from m)"
)


@query("onehop_by_day", _DAYS + O.projected("t", "start") + " select start, c, d, round(v, 6) + 0.0 as v from v")
def onehop_by_day(spark, d):
    """A one-hop K of the event types of each day."""
    days = stream.windowed(stream.class_steps(T.table(spark, d, "events", "ts", "event_id", "user_id", "event_type")))
    types = [r.event_type for r in T.table(spark, d, "events", "event_type").distinct().orderBy("event_type").collect()]  # one row a class
    return estimate.compat_by_group(days, "start", types).select("start", "c", "d", (F.round("v", 6) + 0.0).alias("v"))


_SHARES = "with " + _STEPS + ", n as (select t, (row_number() over (order by t) - 1)::int as i from (select distinct event_type as t from events)), m as (select x.i as c, y.i as d, count(st.b) as n from n x cross join n y left join st on st.a = x.t and st.b = y.t group by all)"


@query("compat_rows", _SHARES + " select c, d, case when sum(n) over (partition by c) > 0 then round(n / sum(n) over (partition by c), 6) else 0.0 end::double as v from m")
def compat_rows(spark, d):
    """The shares of the event types that follow each type, as a matrix in one row, by the SQL table function."""
    estimate.register_sql(spark)
    types = QUERIES["class_dict"](spark, d).select(F.col("cls"), F.col("name"))
    pairs = stream.class_steps(T.table(spark, d, "events", *_EV)).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    grid = types.toDF("c", "a").crossJoin(types.toDF("d", "b")).join(pairs, ["a", "b"], "left").select("c", "d", F.coalesce("n", F.lit(0)).alias("n"))  # a row a pair of types
    total = F.sum("n").over(W.partitionBy("c"))
    shares = grid.select("c", "d", F.when(total > 0, F.round(F.col("n") / total, 6)).otherwise(F.lit(0.0)).alias("v"))
    shares.agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "d", "v"))), lambda x: x["v"]).alias("cells")).createOrReplaceTempView("compat_cells")
    return spark.sql("select t.c, t.d, t.v from compat_cells, lateral compat_rows(cells) t")


@query("label_graph_sql", "select node from (select distinct src as node from (" + O.graph("turns") + " select src from edges))")
def label_graph_sql(spark, d):
    """Every node of the turns that SQL users find labelled, most of its seeds known: those reached are all."""
    edges, labels, _ = turns(spark, d)
    edges.createOrReplaceTempView("turn_edges"), labels.createOrReplaceTempView("turn_seeds")
    estimate.label_graph_sql(spark, "turn_edges", "turn_seeds", 3, "turn_labels_found", "onehop", s=0.5)
    return spark.sql("select node from turn_labels_found left semi join turn_edges on node = src")


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planted_labelled(spark, sf_dir)
