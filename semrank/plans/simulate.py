"""Monte Carlo counts of ranker calls for a perfect ranker: only ranks are simulated, one row per trial."""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.engine import Doc, Judge, tournament_topk
from ..operators.rankers import ColumnRanker
from ..schema import RankParams
from . import cost


def _picked(rng: np.random.Generator, n: int, p: int) -> np.ndarray:
    return np.sort(rng.choice(n, p, replace=False))


def select_calls(rng, n: int, k: int, size: int, p: int, group: int | None = None, early_stop: bool = False) -> int:
    calls, left, group = 0, k, group or p
    while 0 < left < n:
        if n <= size:
            return calls + 1
        m = min(p, n - 1)
        pivots = _picked(rng, n, m)
        calls += m > 1
        rest = n - m
        for start in range(0, m, group):
            own = min(group, m - start)
            asked = rest
            if early_stop and start:
                asked = n - (int(pivots[start - 1]) + 1) - (m - start)  # documents below the last group
            calls += math.ceil(asked / (size - own))
            if early_stop and pivots[start + own - 1] + 1 >= left:
                break
        i = int(np.searchsorted(pivots, left - 1))
        if i < m and pivots[i] == left - 1:
            return calls
        first = int(pivots[i - 1]) + 1 if i else 0
        end = int(pivots[i]) if i < m else n
        n, left = end - first, left - first
    return calls


def sort_calls(rng, n: int, size: int, p: int) -> int:
    calls, todo = 0, [n]
    while todo:
        n = todo.pop()
        if n <= 1:
            continue
        if n <= size:
            calls += 1
            continue
        m = min(p, n - 1)
        calls += (m > 1) + math.ceil((n - m) / (size - m))
        edges = np.concatenate(([-1], _picked(rng, n, m), [n]))
        todo += (np.diff(edges) - 1).tolist()
    return calls


def filter_recall(rng, n: int, k: int, size: int, s: int) -> float:
    return float(np.minimum(np.bincount(rng.choice(n, k, replace=False) // size), s).sum() / k)


def tournament_calls(rng, n: int, k: int, size: int) -> int:
    truth = rng.permutation(n)
    judge = Judge({i: Doc(i, score=float(truth[i])) for i in range(n)}, ColumnRanker(), RankParams(list_size=size, pivots=1), seed=int(rng.integers(1 << 30)))
    tournament_topk(judge, list(range(n)), k)
    return len(judge.calls)


#: Trials of a point, as published.
TRIALS = 5_000
_ONE = {"select": select_calls, "sort": sort_calls, "filter": filter_recall, "tournament": tournament_calls}


def simulate(spark: SparkSession, algo: str, trials: int, seed: int = 42, **config) -> DataFrame:
    """(trial, value): calls, or recall for the filter."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            yield pd.DataFrame({"trial": part["id"], "value": [float(_ONE[algo](np.random.default_rng([seed, int(t)]), **config)) for t in part["id"]]})

    return spark.range(trials).mapInPandas(run, "trial bigint, value double")


def simulate_grid(spark: SparkSession, algo: str, grid: list[dict], trials: int, seed: int = 42) -> DataFrame:
    """(config, value): the mean of ``trials`` per configuration; trials of all configurations are spread over the cluster."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            c = part["id"] // trials
            yield pd.DataFrame({"config": c.astype("int32"), "value": [float(_ONE[algo](np.random.default_rng([seed, int(i)]), **grid[int(g)])) for i, g in zip(part["id"], c, strict=True)]})

    return spark.range(len(grid) * trials).mapInPandas(run, "config int, value double").groupBy("config").agg(F.avg("value").alias("value"))


def compare_theory(spark: SparkSession, algo: str, grid: list[dict], trials: int) -> DataFrame:
    """(config, p, k, simulated, theory, gap)."""
    theory = [(i, int(g.get("p", 0)), int(g.get("k", 0)), float(cost.cost_select(g["n"], g["k"], g["size"], g["p"]) if algo == "select" else cost.cost_sort(g["n"], g["size"], g["p"]))) for i, g in enumerate(grid)]
    known = spark.createDataFrame(theory, "config int, p int, k int, theory double")
    out = simulate_grid(spark, algo, grid, trials).join(known, "config")
    return out.select("config", "p", "k", F.col("value").alias("simulated"), "theory", (F.col("theory") / F.col("value") - 1).alias("gap"))


def fit_sort_coefficient(spark: SparkSession, size: int = 20, p: int = 6, ns: tuple[int, ...] = (100, 1_000, 10_000, 100_000), trials: int = 20) -> float:
    """Least squares of the linear term: simulated calls less the log-linear part, over n."""
    rows = simulate_grid(spark, "sort", [{"n": n, "size": size, "p": p} for n in ns], trials).collect()
    xy = [(ns[r["config"]], r["value"] - cost.cost_sort(ns[r["config"]], size, p, 0.0)) for r in rows]
    return sum(x * y for x, y in xy) / sum(x * x for x, _ in xy)


def exact_select_cost(n: int, k: int, size: int, p: int) -> float:
    """The expected calls of select without the self-similarity assumption: a chain over (documents, rank), for n up to a few hundred."""

    @cache
    def expected(m: int, r: int) -> float:
        if r <= 0 or r >= m:
            return 0.0
        if m <= size:
            return 1.0
        q = min(p, m - 1)
        total, ways = 0.0, math.comb(m, q)
        for first in range(r):
            for width in range(r - first, m - first + 1):
                bounds = (first > 0) + (first + width < m)
                if q >= bounds and m - width - bounds >= q - bounds and (sub := expected(width, r - first)):
                    total += math.comb(m - width - bounds, q - bounds) / ways * sub
        return (q > 1) + math.ceil((m - q) / (size - q)) + total

    return expected(n, k)
