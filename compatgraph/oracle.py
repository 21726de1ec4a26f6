"""DuckDB texts: fixtures and unrolled iterations, written apart from the engine's plans."""

from __future__ import annotations

import numpy as np

EDGES = {
    "trade": "raw as (select 2 * o_custkey as a, 2 * l_suppkey + 1 as b, count(*)::double as w from lineitem join orders on l_orderkey = o_orderkey group by all)",
    "copart": "raw as (select x.l_partkey as a, y.l_partkey as b, count(*)::double as w from (select distinct l_orderkey, l_partkey from lineitem) x join (select distinct l_orderkey, l_partkey from lineitem) y on x.l_orderkey = y.l_orderkey and x.l_partkey < y.l_partkey group by all)",
    "turns": "raw as (select * from (select conv_id * 4096 + turn as a, conv_id * 4096 + lead(turn) over (partition by conv_id order by turn) as b, 1.0::double as w from conversations) where b is not null)",
    "steps": "raw as (select * from (select event_id as a, lead(event_id) over (partition by user_id order by ts, event_id) as b, 1.0::double as w from events) where b is not null)",
    "tree": "raw as (select 4 * n_regionkey::bigint as a, 4 * n_nationkey::bigint + 1 as b, 1.0::double as w from nation union all select 4 * c_nationkey::bigint + 1, 4 * c_custkey + 2, 1.0 from customer union all select 4 * s_nationkey::bigint + 1, 4 * s_suppkey + 3, 1.0 from supplier)",
    "docs": "raw as (select * from (select min(doc_id) over (partition by text) as a, doc_id as b, 1.0::double as w from documents) where a <> b)",
    "pages": """raw as (select 2 * page_id as a, 2 * ('0x' || substr(md5(h), 1, 12))::bigint + 1 as b, 1.0::double as w from (select page_id, unnest(list_distinct(regexp_extract_all(html, '<a href="([^"]*)"', 1))) as h from pages))""",
}
BOTH = "edges as (select a as src, b as dst, w from raw union all select b, a, w from raw)"
LABELS = {
    "turns": "labels as (select conv_id * 4096 + turn as node, (case role when 'assistant' then 0 when 'system' then 1 else 2 end)::int as cls from conversations)",
    "trade": "labels as (select 2 * c_custkey as node, n_regionkey::int as cls from customer join nation on c_nationkey = n_nationkey union all select 2 * s_suppkey + 1, n_regionkey::int from supplier join nation on s_nationkey = n_nationkey)",
}


def u(key: str) -> str:
    return f"('0x' || substr(md5(({key})::varchar), 1, 8))::bigint"


def graph(name: str, f: float | None = None) -> str:
    """Leading WITH of edges, and of labels and seeds where the fixture has them."""
    out = f"with {EDGES[name]}, {BOTH}"
    if name in LABELS:
        out += f", {LABELS[name]}, seeds as (select * from labels" + (f" where {u('node')} < {int(f * 2**32)}" if f is not None else "") + ")"
    return out


def scaled(alpha: float, beta: float, gamma: float = 0.0) -> str:
    p = "edges"
    out = ""
    if alpha or beta:
        out = f", deg as (select src as node, sum(w) as deg from edges group by src), p0 as (select e.src, e.dst, e.w * pow(x.deg, {-alpha}) * pow(y.deg, {-beta}) as w from edges e join deg x on x.node = e.src join deg y on y.node = e.dst)"
        p = "p0"
    if gamma == 1:
        return out + f", p as (select * from {p} where src not in (select node from seeds))"
    return out + f", p as (select q.src, q.dst, q.w * (1 - {gamma} * (s.node is not null)::int) as w from {p} q left join seeds s on s.node = q.src)"


def linear(K, prefix: str = "b") -> list[str]:
    k = len(K)
    return [" + ".join(f"{prefix}{c} * {float(K[c][d])!r}" for c in range(k)) for d in range(k)]


def residual(k: int) -> str:
    return ", x as (select node, " + ", ".join(f"(cls = {c})::int - {1 / k!r} as b{c}" for c in range(k)) + " from seeds)"


def iterate(K, eps: float, r: int, echo: bool = False, start: str = "x", keep: float | None = 1.0) -> str:
    """States s1 .. sr; each update adds ``keep`` of x, or nothing of it."""
    k = len(K)
    out = ", q as (select a.src as node, sum(a.w * b.w) as q from p a join p b on a.src = b.dst and a.dst = b.src group by a.src)" if echo else ""
    for i in range(1, r + 1):
        last = start if i == 1 else f"s{i - 1}"
        m = ", ".join(f"{e} as b{d}" for d, e in enumerate(linear(K)))
        own = "" if keep is None else "select * from x union all " if keep == 1 else f"select node, {', '.join(f'{keep!r} * b{c} as b{c}' for c in range(k))} from x union all "
        parts = own + f"select p.src as node, {', '.join(f'{eps!r} * sum(p.w * m.b{d}) as b{d}' for d in range(k))} from p join (select node, {m} from {last}) m on m.node = p.dst group by p.src"
        if echo:
            two = linear(np.asarray(K) @ np.asarray(K), "v.b")
            parts += f" union all select v.node, {', '.join(f'{-eps * eps!r} * q.q * ({e})' for e in two)} from {last} v join q on q.node = v.node"
        out += f", s{i} as materialized (select node, {', '.join(f'sum(b{c}) as b{c}' for c in range(k))} from ({parts}) group by node)"
    return out


def predicted(state: str, name: str) -> str:
    """CTE ``name`` (node, cls) of a state of three classes, by nine digits."""
    return f", {name} as (select node, case when round(b0, 9) >= round(greatest(b1, b2), 9) then 0 when round(b1, 9) >= round(b2, 9) then 1 else 2 end as cls from {state})"


def projected(t: str, by: str = "") -> str:
    """CTEs from ``t`` (by, c, d, t) to the nearest symmetric three-class-or-more matrix with rows of sum 1: ``v`` (by, c, d, v); k is counted."""
    g, on = (f"{by}, ", lambda a, b: f"a.{by} = b.{by} and ") if by else ("", lambda a, b: "")
    link = lambda x, col: f"join u {x} on {f'{x}.{by} = y.{by} and ' if by else ''}{x}.c = y.{col}"
    same = on("a", "b")
    return (
        f", kk as (select count(distinct c) as k from {t}), y as (select {f'a.{by}, ' if by else ''}a.c, a.d, (a.t + b.t) / 2 as s from {t} a join {t} b on {same}a.c = b.d and a.d = b.c)"
        f", rho as (select {g}c, 1 - sum(s) as rho from y group by {g}c), u as (select {g}c, (rho - sum(rho) over ({f'partition by {by}' if by else ''}) / (2 * k)) / k as u from rho, kk)"
        f", v as (select {f'y.{by}, ' if by else ''}y.c, y.d, s + p.u + q.u as v from y {link('p', 'c')} {link('q', 'd')})"
    )


def energy_solved(m: str) -> str:
    """CTE ``h`` of three unknowns from one row of moments ``m`` (nn_cd, nx_cd): normal equations by Cramer's rule.

    K = [[a, b, 1-a-b], [b, e, 1-b-e], [1-a-b, 1-b-e, a+2b+e-1]].
    """
    slopes = {"a": {(0, 0): 1, (0, 2): -1, (2, 0): -1, (2, 2): 1}, "b": {(0, 1): 1, (1, 0): 1, (0, 2): -1, (2, 0): -1, (1, 2): -1, (2, 1): -1, (2, 2): 2}, "e": {(1, 1): 1, (1, 2): -1, (2, 1): -1, (2, 2): 1}}
    fixed = {(0, 2): 1, (2, 0): 1, (1, 2): 1, (2, 1): 1, (2, 2): -1}
    product = lambda x, y: " + ".join(f"{f * g} * nn_{r}{t}" for (r, c), f in x.items() for (t, c2), g in y.items() if c == c2) or "0"
    cells = [f"{product(x, y)} as a{i}{j}" for i, x in enumerate(slopes.values()) for j, y in enumerate(slopes.values())]
    cells += [" + ".join(f"{f} * nx_{r}{c}" for (r, c), f in x.items()) + f" - ({product(x, fixed)}) as r{i}" for i, x in enumerate(slopes.values())]
    det = lambda n: f"({n(0, 0)} * ({n(1, 1)} * {n(2, 2)} - {n(1, 2)} * {n(2, 1)}) - {n(0, 1)} * ({n(1, 0)} * {n(2, 2)} - {n(1, 2)} * {n(2, 0)}) + {n(0, 2)} * ({n(1, 0)} * {n(2, 1)} - {n(1, 1)} * {n(2, 0)}))"
    whole = det(lambda i, j: f"a{i}{j}")
    solved = ", ".join(f"{det(lambda i, j, x=x: f'r{i}' if j == x else f'a{i}{j}')} / {whole} as {n}" for x, n in enumerate(slopes))
    return f", normal as (select {', '.join(cells)} from {m}), h as (select {solved} from normal)"


def beliefs_of_messages(K, r: int, prior: float = 0.9) -> str:
    """Loopy beliefs of three classes by products of messages, with ``edges`` and ``seeds`` given; the last CTE is ``bel``."""
    k = len(K)
    low = (1 - prior) / (k - 1)
    out = ", pr as (select node, " + ", ".join(f"case when cls = {c} then {prior!r} when cls is null then {1 / k!r} else {low!r} end as p{c}" for c in range(k)) + " from (select distinct src as node from edges) left join seeds using (node))"
    out += ", m0 as (select src, dst, " + ", ".join(f"1.0::double as b{c}" for c in range(k)) + " from edges)"
    for i in range(r + 1):
        out += f", f{i} as materialized (select n.node, {', '.join(f'any_value(n.p{c}) * product(m.b{c}) as b{c}' for c in range(k))} from pr n join m{i} m on m.dst = n.node group by n.node)"
        if i < r:
            raw = ", ".join(" + ".join(f"f.b{c} / o.b{c} * {float(K[c][d])!r}" for c in range(k)) + f" as c{d}" for d in range(k))
            top = f"greatest({', '.join(f'c{d}' for d in range(k))})"
            out += f", m{i + 1} as materialized (select src, dst, {', '.join(f'c{d} / {top} as b{d}' for d in range(k))} from (select e.src, e.dst, {raw} from edges e join f{i} f on f.node = e.src join m{i} o on o.src = e.dst and o.dst = e.src))"
    total = " + ".join(f"b{c}" for c in range(k))
    return out + f", bel as (select node, {', '.join(f'b{c} / ({total}) as b{c}' for c in range(k))} from f{r})"


def rounded(k: int, digits: int = 6) -> str:
    return "node, " + ", ".join(f"round(b{c}, {digits}) + 0.0 as b{c}" for c in range(k))


def pairs(k: int, n: str) -> str:
    """c, d, cnt of seeds against a state ``n``."""
    grid = f"(select c::int as c, d::int as d from range({k}) t(c), range({k}) v(d))"
    each = " union all ".join(f"select s.cls as c, {d} as d, sum(b{d})::bigint as n from seeds s join {n} t on t.node = s.node group by s.cls" for d in range(k))
    return f"select g.c, g.d, coalesce(m.n, 0)::bigint as cnt from {grid} g left join ({each}) m on m.c = g.c and m.d = g.d"


def hops(k: int, l: int, back: bool = False) -> str:
    out = f", n0 as (select node, {', '.join(f'(cls = {c})::bigint as b{c}' for c in range(k))} from seeds), dg as (select src as node, count(*) as deg from edges group by src)"
    for i in range(1, l + 1):
        parts = f"select e.src as node, {', '.join(f'sum(b{c}) as b{c}' for c in range(k))} from edges e join n{i - 1} n on n.node = e.dst group by e.src"
        if not back and i > 1:
            less = "g.deg" if i == 2 else "(g.deg - 1)"
            parts += f" union all select n.node, {', '.join(f'-{less} * b{c}' for c in range(k))} from n{i - 2} n join dg g on g.node = n.node"
        out += f", n{i} as materialized (select node, {', '.join(f'sum(b{c})::bigint as b{c}' for c in range(k))} from ({parts}) group by node)"
    return out
