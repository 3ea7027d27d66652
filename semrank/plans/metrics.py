"""Accuracy and cost measures over result, gold and ledger tables."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def count_calls(calls: DataFrame, *by: str) -> DataFrame:
    return calls.groupBy(*by).agg(F.count("*").alias("calls"), F.sum("n_items").alias("items"), F.sum("chars_in").alias("chars"))


def critical_path(calls: DataFrame, workers: int) -> DataFrame:
    """Waves of calls that must follow one another with so many workers, per scope."""
    return calls.groupBy("scope", "round", "kind").agg(F.ceil(F.count("*") / workers).alias("w")).groupBy("scope").agg(F.sum("w").alias("waves"))


def quality_rates(calls: DataFrame) -> DataFrame:
    return calls.groupBy("algo").agg(F.avg(F.col("repaired").cast("int")).alias("repaired"), F.avg(F.col("contradiction").cast("int")).alias("contradictions"))


def implied_pairs(calls: DataFrame) -> DataFrame:
    """Pairwise comparisons that the lists imply, and the bits of their orders."""
    n = F.col("n_items")
    return calls.groupBy("algo").agg(F.count("*").alias("calls"), F.sum(n * (n - 1) / 2).alias("pairs"), F.sum(F.aggregate(F.sequence(F.lit(1), n), F.lit(0.0), lambda a, x: a + F.log2(x))).alias("bits"))


def timed(run: Callable[[], DataFrame]) -> tuple[float, int]:
    """Seconds and rows of a forced run."""
    start = time.perf_counter()
    n = run().count()
    return time.perf_counter() - start, n


def recall_at_k(topk: DataFrame, gold: DataFrame, k: int, denominator: str = "gold") -> DataFrame:
    """(scope, recall). gold: (scope, id). denominator: all relevant documents, or at most k of them."""
    total = gold.groupBy("scope").agg(F.countDistinct("id").alias("n"))
    first = topk.filter(F.col("rank").isNull() | (F.col("rank") <= k)).select("scope", "id").distinct()
    hits = gold.select("scope", "id").distinct().join(first, ["scope", "id"], "left_semi").groupBy("scope").agg(F.count("*").alias("h"))
    n = F.col("n") if denominator == "gold" else F.least("n", F.lit(k))
    return total.join(hits, "scope", "left").select("scope", (F.coalesce("h", F.lit(0)) / n).alias("recall"))


def ndcg_at_k(topk: DataFrame, qrels: DataFrame, k: int, gain: str = "linear") -> DataFrame:
    """(scope, ndcg). qrels: (scope, id, rel)."""
    value = (lambda c: c.cast("double")) if gain == "linear" else (lambda c: F.pow(F.lit(2.0), c) - 1)
    discount = lambda rank: 1 / F.log2(rank + 1)
    ideal = qrels.withColumn("i", F.row_number().over(W.partitionBy("scope").orderBy(F.desc("rel"), "id"))).filter(F.col("i") <= k).groupBy("scope").agg(F.sum(value(F.col("rel")) * discount(F.col("i"))).alias("ideal"))
    got = topk.filter(F.col("rank") <= k).join(qrels, ["scope", "id"]).groupBy("scope").agg(F.sum(value(F.col("rel")) * discount(F.col("rank"))).alias("dcg"))
    return ideal.join(got, "scope", "left").select("scope", F.when(F.col("ideal") > 0, F.coalesce("dcg", F.lit(0.0)) / F.col("ideal")).otherwise(F.lit(0.0)).alias("ndcg"))


def mid_rank(value: Column, *scope: str) -> Column:
    """Ranks from 1 where ties share their mean place."""
    w = W.partitionBy(*scope).orderBy(value)
    return F.rank().over(w) + (F.count("*").over(W.partitionBy(*scope, value)) - 1) / 2


def spearman(pred: DataFrame, gold: DataFrame) -> DataFrame:
    """(scope, spearman). pred and gold: (scope, id, value), both in the same direction."""
    both = pred.select("scope", "id", F.col("value").alias("a")).join(gold.select("scope", "id", F.col("value").alias("b")), ["scope", "id"])
    ranked = both.select("scope", mid_rank(F.col("a"), "scope").alias("x"), mid_rank(F.col("b"), "scope").alias("y"))
    return ranked.groupBy("scope").agg(F.corr("x", "y").alias("spearman"))


def summarise(metrics: DataFrame, value: str, *by: str) -> DataFrame:
    v = F.col(value)
    return metrics.groupBy(*by).agg(F.avg(v).alias("mean"), F.min(v).alias("least"), F.max(v).alias("most"), F.percentile(v, F.lit(0.5)).alias("median"), F.percentile(v, F.lit(0.95)).alias("p95"), F.count("*").alias("n"))


def speedup(metrics: DataFrame, base: str, value: str = "calls") -> DataFrame:
    """(algo, value, speedup over ``base``, relative overhead in percent)."""
    means = metrics.groupBy("algo").agg(F.avg(value).alias("value"))
    one = means.filter(F.col("algo") == base).select(F.col("value").alias("base"))
    return means.crossJoin(F.broadcast(one)).select("algo", "value", (F.col("base") / F.col("value")).alias("speedup"), (100 * (F.col("value") / F.col("base") - 1)).alias("overhead_pct"))


def pareto(metrics: DataFrame, cost: str = "calls", gain: str = "accuracy") -> DataFrame:
    """Methods that no other beats in both; one row per method, a small table."""
    a, b = metrics.alias("a"), metrics.alias("b")
    beaten = (F.col(f"b.{cost}") <= F.col(f"a.{cost}")) & (F.col(f"b.{gain}") >= F.col(f"a.{gain}")) & ((F.col(f"b.{cost}") < F.col(f"a.{cost}")) | (F.col(f"b.{gain}") > F.col(f"a.{gain}")))
    return a.join(b, beaten, "left_anti")


def _solve(m: list[list[float]], v: list[float]) -> list[float]:
    rows = [[*r, x] for r, x in zip(m, v, strict=True)]
    for i in range(len(rows)):
        p = max(range(i, len(rows)), key=lambda r: abs(rows[r][i]))
        rows[i], rows[p] = rows[p], rows[i]
        rows[i] = [x / rows[i][i] for x in rows[i]]
        for j in range(len(rows)):
            if j != i:
                rows[j] = [x - rows[j][i] * y for x, y in zip(rows[j], rows[i], strict=True)]
    return [r[-1] for r in rows]


def fit(df: DataFrame, x: str, y: str, kind: str = "linear") -> list[float]:
    """Least squares from sums alone. linear: a x + b; quadratic: a x^2 + b x + c; reciprocal: a x + b + c / x."""
    basis = {"linear": [F.col(x), F.lit(1.0)], "quadratic": [F.col(x) * F.col(x), F.col(x), F.lit(1.0)], "reciprocal": [F.col(x), F.lit(1.0), 1 / F.col(x)]}[kind]
    n = len(basis)
    sums = [F.sum((basis[i] * basis[j]).cast("double")) for i in range(n) for j in range(n)] + [F.sum((b * F.col(y)).cast("double")) for b in basis]
    got = list(df.agg(*(s.alias(f"s{i}") for i, s in enumerate(sums))).first())
    return _solve([got[i * n : i * n + n] for i in range(n)], got[n * n :])


def best_list_size(a: float, c: float) -> float:
    """Where a x + b + c / x is least."""
    return math.sqrt(c / a)
