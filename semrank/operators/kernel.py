"""The ranking kernel: lists in, orders out. One row is one call.

A call is named by scope, phase, segment, round, kind and its place in the round; the name is the same whether a task
makes the call by itself (``engine``) or a Spark job makes all calls of a round, and rankers with noise depend on it.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass
from functools import lru_cache

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..schema import RankParams
from .prompts import repair_ranking
from .rankers import ListRequest, Ranker


@dataclass
class Ranked:
    """A result and the ledger of the calls that made it."""

    rows: DataFrame
    calls: DataFrame


@lru_cache(maxsize=1 << 15)
def _place(seed, turn, i: int) -> tuple[str, int]:
    return hashlib.md5(f"{seed}:{turn}:{i}".encode()).hexdigest(), i


def shuffled(ids: list[int], seed, turn) -> list[int]:
    return sorted(ids, key=lambda i: _place(seed, turn, i))


def call_name(scope, phase: str, seg, turn, kind: str, place="") -> str:
    return f"{scope}:{phase}:{seg}:{turn}:{kind}:{place}"


def answered(ranker: Ranker, calls: list[ListRequest], seed, params: RankParams, votes: int = 1) -> list[tuple[list[int], list[bool], list[bool]]]:
    """For each call: positions of its documents from 0, best first; and for each vote whether the response was repaired and contradicted the pivots.

    Pivots stand first in their settled order; the others in slots by a hash, or as they come. With more votes than one
    each is a response to other slots, and mean places decide (ties by id).
    """
    asked, slots = [], []
    for c in calls:
        for vote in range(votes):
            rest = list(range(c.pivots, len(c.ids)))
            if params.slot_order == "hash":
                place = {i: n for n, i in enumerate(shuffled([c.ids[p] for p in rest], seed, f"slot{vote}"))}
                rest.sort(key=lambda p: place[c.ids[p]])
            slot = [*range(c.pivots), *rest]
            slots.append(slot)
            name = c.call_id if votes == 1 else f"{c.call_id}#{vote}"
            asked.append(ListRequest(name, [c.ids[p] for p in slot], [c.payloads[p] for p in slot], [c.scores[p] for p in slot], c.query, c.pivots))
    responses = iter(zip(ranker.rank(asked) if asked else [], slots, strict=True))
    out = []
    for c in calls:
        total, order, repaired, contradicted = [0.0] * len(c.ids), [], [], []
        for _ in range(votes):
            response, slot = next(responses)
            fixed, changed = repair_ranking([p + 1 for p in response], len(c.ids))
            order = [slot[p - 1] for p in fixed]
            repaired.append(changed)
            contradicted.append(c.pivots > 1 and [p for p in order if p < c.pivots] != list(range(c.pivots)))
            for place, p in enumerate(order):
                total[p] += place
        out.append((order if votes == 1 else sorted(range(len(c.ids)), key=lambda p: (total[p], c.ids[p])), repaired, contradicted))
    return out


def lists_of(binned: DataFrame, keys: list[str], kind: str) -> DataFrame:
    """(keys, bin, kind, n_pivots, docs): the documents of a bin as an array in slot order."""
    got = binned.groupBy(*keys, "bin").agg(F.sort_array(F.collect_list(F.struct("slot", "id", "payload", "score"))).alias("_d"))
    docs = F.transform("_d", lambda d: F.struct(d["id"].alias("id"), d["payload"].alias("payload"), d["score"].alias("score")))
    return got.select(*keys, "bin", F.lit(kind).alias("kind"), F.lit(0).alias("n_pivots"), docs.alias("docs"))


def named(lists: DataFrame, phase: str, turn, place: Column, seg: Column | None = None) -> DataFrame:
    """Adds ``call_id``: ``call_name`` as a column."""
    parts = (F.col("scope").cast("string"), F.lit(phase), F.lit("0") if seg is None else seg.cast("string"), F.lit(str(turn)), F.col("kind"), place.cast("string"))
    return lists.withColumn("call_id", F.concat_ws(":", *parts))


def _native_order(docs: Column) -> Column:
    keyed = F.transform(docs, lambda d: F.struct(F.coalesce(-d["score"], F.lit(float("inf"))).alias("k"), d["id"].alias("id"), d["payload"].alias("payload"), d["score"].alias("score")))
    return F.transform(F.array_sort(keyed), lambda d: F.struct(d["id"].alias("id"), d["payload"].alias("payload"), d["score"].alias("score")))


def rank_lists(lists: DataFrame, ranker: Ranker, queries: DataFrame | None = None, params: RankParams | None = None, seed=42, votes: int = 1) -> DataFrame:
    """Adds ``ranked`` (docs, best first) and, for each vote, ``repaired`` and ``contradicted``. A perfect ranker on a column stays in the JVM.

    queries: (scope, query). Lists of one document aren't calls; they come back as they are. The function is marked as
    not deterministic, since a model may answer twice in two ways: Spark then neither repeats nor moves the calls.
    """
    params = params or RankParams()
    if "call_id" not in lists.columns:
        lists = lists.withColumn("call_id", F.concat_ws(":", F.col("scope").cast("string"), F.col("kind"), F.col("bin").cast("string")))
    if ranker.native:
        never = F.array_repeat(F.lit(False), votes)
        return lists.withColumns({"ranked": _native_order(F.col("docs")), "repaired": never, "contradicted": never})
    if queries is not None:
        lists = lists.join(queries.select("scope", "query"), "scope", "left")
    else:
        lists = lists.withColumn("query", F.lit(""))
    if params.workers:
        lists = lists.repartition(params.workers)

    def order(call: pd.Series, ids: pd.Series, payloads: pd.Series, scores: pd.Series, query: pd.Series, pivots: pd.Series) -> pd.DataFrame:
        many = [i for i in range(len(ids)) if len(ids.iloc[i]) > 1]
        requests = [ListRequest(str(call.iloc[i]), [int(x) for x in ids.iloc[i]], list(payloads.iloc[i]), [None if x is None or x != x else float(x) for x in scores.iloc[i]], query.iloc[i] or "", int(pivots.iloc[i])) for i in many]
        out: list = [([1] if len(x) else [], [], []) for x in ids]
        for i, (got, repaired, contradicted) in zip(many, answered(ranker, requests, seed, params, votes), strict=True):
            out[i] = ([p + 1 for p in got], repaired, contradicted)
        return pd.DataFrame(out, columns=["order", "repaired", "contradicted"])

    udf = F.pandas_udf(order, "order array<int>, repaired array<boolean>, contradicted array<boolean>").asNondeterministic()
    got = lists.withColumn("_o", udf("call_id", F.col("docs.id"), F.col("docs.payload"), F.col("docs.score"), F.coalesce("query", F.lit("")), F.col("n_pivots")))
    return got.withColumns({"ranked": F.transform(F.col("_o.order"), lambda p: F.element_at("docs", p)), "repaired": F.col("_o.repaired"), "contradicted": F.col("_o.contradicted")}).drop("_o", "query")


def counted(ranked: DataFrame) -> DataFrame:
    """Ranked lists as they are kept: ``n_items`` and ``chars_in`` for the ledger instead of the documents in slot order."""
    chars = F.aggregate("docs", F.lit(0).cast("long"), lambda a, d: a + F.coalesce(F.length(d["payload"]), F.lit(0)))
    return ranked.withColumns({"n_items": F.size("docs"), "chars_in": chars}).drop("docs")


def ledger_of(ranked: DataFrame, run_id: str, algo: str, turn: int) -> DataFrame:
    """One row per call, from the materialised lists (``counted``); each vote is a call."""
    n_votes = F.size("repaired")
    call = F.when(n_votes > 1, F.concat_ws("#", "call_id", F.col("v.at").cast("string"))).otherwise(F.col("call_id"))
    votes = ranked.filter("n_items > 1").withColumn("v", F.explode(F.transform(F.arrays_zip("repaired", "contradicted"), lambda x, i: F.struct(i.alias("at"), x["repaired"].alias("repaired"), x["contradicted"].alias("contradicted")))))
    return votes.select(
        F.lit(run_id).alias("run_id"), F.lit(algo).alias("algo"), "scope", F.lit(turn).alias("round"), call.alias("call_id"), "kind",
        "n_items", F.col("n_pivots").cast("int").alias("n_pivots"), "chars_in",
        F.col("v.repaired").alias("repaired"), F.col("v.contradicted").alias("contradiction"),
    )
