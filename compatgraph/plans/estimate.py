"""Compatibility estimators: one-hop, energy fit and multi-hop.  Spark reduces the graph to k x k statistics, the driver solves."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..functions.compat import empty_rows, fit_powers, nearest_compat, normalize_counts, solve_energy
from ..operators.labels import names, one_hot, predict
from .propagate import operator, propagate, send
from .walks import count_matrices


def estimate_onehop(edges: DataFrame, seeds: DataFrame, k: int, variant: int = 1, nonneg: bool = False, residual: bool = False) -> np.ndarray:
    """With ``residual`` the matrix less 1/k, fitted in residual form."""
    T = normalize_counts(count_matrices(edges, seeds, k, 1)[0], variant)
    return nearest_compat(T - 1 / k, total=0.0) if residual else nearest_compat(T, nonneg)


def estimate_multihop(edges: DataFrame, seeds: DataFrame, k: int, lmax: int = 5, lam: float = 10.0, variant: int = 1, backtracking: bool = False, residual: bool = False) -> np.ndarray:
    return fit_powers([normalize_counts(M, variant) for M in count_matrices(edges, seeds, k, lmax, backtracking)], lam, residual=residual)[0]


@dataclass
class EstimateReport:
    """What an estimate rests on: labelled pairs a hop, classes without any (their rows were taken as uniform), and the fit's loss."""

    K: np.ndarray
    pairs: list[int]
    empty_rows: list[list[int]]
    loss: float


def estimate_report(edges: DataFrame, seeds: DataFrame, k: int, lmax: int = 5, lam: float = 10.0, variant: int = 1, backtracking: bool = False) -> EstimateReport:
    M = count_matrices(edges, seeds, k, lmax, backtracking)
    K, loss = fit_powers([normalize_counts(m, variant) for m in M], lam)
    return EstimateReport(K, [int(m.sum()) for m in M], [empty_rows(m) for m in M], loss)


def energy_moments(edges: DataFrame, seeds: DataFrame, k: int, *, alpha=0.0, beta=0.0, gamma=0.0, rows: str = "all") -> DataFrame:
    """One row of N'N (nn_cd) and N'X (nx_cd) with N = P X: one pass over the graph, whatever the solver does.

    ``rows``: all nodes, or the labelled ones only (others add the size of their neighbours' mean to the energy).
    """
    N = send(operator(edges, seeds, alpha, beta, gamma), one_hot(seeds, k).select("node", *[F.col(c).cast("double").alias(c) for c in names(k)]), k)
    both = N.join(one_hot(seeds, k).select("node", *[F.col(f"b{c}").alias(f"x{c}") for c in range(k)]), "node", {"all": "left", "labelled": "inner"}[rows])
    sums = [F.sum(F.col(f"b{c}") * F.col(f"b{d}")).alias(f"nn_{c}{d}") for c in range(k) for d in range(k)]
    sums += [F.sum(F.col(f"b{c}") * F.coalesce(f"x{d}", F.lit(0))).alias(f"nx_{c}{d}") for c in range(k) for d in range(k)]
    return both.agg(*sums)


def estimate_energy(edges: DataFrame, seeds: DataFrame, k: int, *, mode: str = "free", rows: str = "all", **scaling) -> np.ndarray:
    row = np.array([v or 0.0 for v in energy_moments(edges, seeds, k, rows=rows, **scaling).first()])
    return solve_energy(row[: k * k].reshape(k, k), row[k * k :].reshape(k, k), mode)


ESTIMATORS = {"onehop": estimate_onehop, "multihop": estimate_multihop, "energy": estimate_energy}


def label_graph(edges: DataFrame, seeds: DataFrame, k: int, estimator: str = "multihop", **options) -> DataFrame:
    """Estimate K from the seeds, propagate with it, and predict every reached node."""
    K = ESTIMATORS[estimator](edges, seeds, k)
    return predict(propagate(edges, seeds, K, **({"beta": 1.0, "gamma": 0.5, "s": 3.0} | options)), k)


def compat_by_group(pairs: DataFrame, group: str, classes: list, variant: int = 1) -> DataFrame:
    """group, c, d, v: a one-hop K of each group from its class-pair counts (a, b, n); a group's task gets its k x k counts only."""
    at = {c: i for i, c in enumerate(classes)}
    kind = pairs.schema[group].dataType.simpleString()
    counted = pairs.groupBy(group, "a", "b").agg(F.sum("n").alias("n"))

    def solve(frame):
        M = np.zeros((len(at), len(at)))
        for a, b, n in zip(frame["a"], frame["b"], frame["n"], strict=True):
            M[at[a], at[b]] += n
            M[at[b], at[a]] += n
        K = nearest_compat(normalize_counts(M, variant))
        own = [(frame[group].iloc[0], i, j, float(K[i, j])) for i in range(len(at)) for j in range(len(at))]
        return pd.DataFrame(own, columns=[group, "c", "d", "v"])

    return counted.groupBy(group).applyInPandas(solve, f"{group} {kind}, c int, d int, v double")


class CompatRows:
    """SQL table function: ``compat_rows(cells)`` turns row-major K, as an array, into rows (c, d, v)."""

    def eval(self, cells):
        k = round(len(cells) ** 0.5)
        for i, v in enumerate(cells):
            yield i // k, i % k, v


def register_sql(spark) -> None:
    """Make ``compat_rows`` known to the session's SQL."""
    spark.udtf.register("compat_rows", udtf(CompatRows, returnType="c int, d int, v double"))


def label_graph_sql(spark, edges: str, seeds: str, k: int, into: str, estimator: str = "multihop", **options) -> None:
    """For SQL users: labels the graph of two tables or views and leaves the predictions as a view ``into``."""
    found = label_graph(spark.table(edges), spark.table(seeds), k, estimator, **options)
    found.createOrReplaceTempView(into)
