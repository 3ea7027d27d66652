"""Baselines: pairwise select and sort, pointwise scoring, Elo from all pairs, and a retriever ensemble for gold rankings."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..schema import RankParams
from ..sources.tables import bound_batches, materialise
from .kernel import Ranked
from .rankers import ColumnRanker, ListRequest, PointScorer, Ranker, parse_score
from .retrieval import fused_best
from .topk import pivot_topk

_PAIR = RankParams(list_size=2, pivots=1)


def pairwise_prior(items: DataFrame, k: int, ranker: Ranker, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None) -> Ranked:
    """Quickselect and quicksort by pairs, pivots by proxy; meant for a general-purpose ranker."""
    return pivot_topk(items, k, ranker, _PAIR.but(pivot_mode="proxy"), seed, queries, tail)


def pairwise_list(items: DataFrame, k: int, ranker: Ranker, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None) -> Ranked:
    """The same on the listwise ranker with lists of two and random pivots."""
    return pivot_topk(items, k, ranker, _PAIR, seed, queries, tail)


def score_points(items: DataFrame, scorer: PointScorer, queries: DataFrame | None = None) -> DataFrame:
    """items with ``response`` and ``score``, the response as a number (invalid: half of the largest) and ``valid``."""
    x = items.join(queries, "scope", "left") if queries is not None else items.withColumn("query", F.lit(""))
    schema = "scope bigint, id bigint, response string, score double, valid boolean"
    names = [c.split(" ")[0] for c in schema.split(", ")]

    def many(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            texts = scorer.responses(part["id"].tolist(), part["score"].astype(object).where(part["score"].notna(), None).tolist())
            known = {x: parse_score(x, scorer.top) for x in set(texts)}
            yield pd.DataFrame({"scope": part["scope"], "id": part["id"], "response": texts, "score": [known[x][0] for x in texts], "valid": [known[x][1] for x in texts]}, columns=names)

    if type(scorer) is PointScorer and type(scorer.base) is ColumnRanker:
        return x.select("scope", "id", "score").mapInPandas(many, schema)

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            out = []
            for scope, i, payload, score, query in zip(part["scope"], part["id"], part["payload"], part["score"], part["query"], strict=True):
                text = scorer.respond(ListRequest(f"{scope}:{i}", [int(i)], [payload], [None if pd.isna(score) else score], query or ""))
                out.append((scope, i, text, *parse_score(text, scorer.top)))
            yield pd.DataFrame(out, columns=names)

    return x.select("scope", "id", "payload", "score", "query").mapInPandas(run, schema)


def parsed_score(response: Column, top: float) -> Column:
    """The same parsing as a column."""
    return F.coalesce(F.trim(response).try_cast("double"), F.lit(top / 2))


def pointwise_topk(items: DataFrame, k: int, scorer: PointScorer, queries: DataFrame | None = None) -> Ranked:
    """Score, then sort by score and id."""
    scored = materialise(score_points(items, scorer, queries), "points")
    w = W.partitionBy("scope").orderBy(F.desc("score"), "id")
    rows = scored.withColumn("rank", F.row_number().over(w).cast("long")).filter(F.col("rank") <= k).select("scope", "rank", "id")
    calls = scored.select(F.lit("").alias("run_id"), F.lit("pointwise").alias("algo"), "scope", F.lit(0).alias("round"), F.concat_ws(":", F.col("scope").cast("string"), F.col("id").cast("string")).alias("call_id"), F.lit("point").alias("kind"), F.lit(1).alias("n_items"), F.lit(0).alias("n_pivots"), F.lit(0).cast("long").alias("chars_in"), (~F.col("valid")).alias("repaired"), F.lit(False).alias("contradiction"))
    return Ranked(rows, calls)


def elo_rank(pairs: DataFrame, k_factor: float = 32.0, start: float = 1000.0) -> DataFrame:
    """(scope, id, rating, gold_rank) from (scope, winner, loser): one pass over each scope's pairs in order of (winner, loser) hash."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        rating: dict[int, float] = {}
        order = part.assign(h=[hash((int(a) * 1_000_003) ^ int(b)) % 1_000_003 for a, b in zip(part["winner"], part["loser"], strict=True)]).sort_values(["h", "winner", "loser"])
        for a, b in zip(order["winner"], order["loser"], strict=True):
            x, y = rating.setdefault(int(a), start), rating.setdefault(int(b), start)
            gain = k_factor * (1 - 1 / (1 + 10 ** ((y - x) / 400)))
            rating[int(a)], rating[int(b)] = x + gain, y - gain
        ranked = sorted(rating, key=lambda i: (-rating[i], i))
        return pd.DataFrame({"scope": part["scope"].iloc[0], "id": ranked, "rating": [rating[i] for i in ranked], "gold_rank": range(1, len(ranked) + 1)})

    return pairs.groupBy("scope").applyInPandas(run, "scope bigint, id bigint, rating double, gold_rank bigint")


def all_pairs(cands: DataFrame) -> DataFrame:
    """(scope, winner, loser) of every pair of a scope's candidates by their score; a stated, short list per scope."""
    a, b = cands.alias("a"), cands.alias("b")
    better = (F.col("a.score") > F.col("b.score")) | ((F.col("a.score") == F.col("b.score")) & (F.col("a.id") < F.col("b.id")))
    return a.join(b, (F.col("a.scope") == F.col("b.scope")) & (F.col("a.id") != F.col("b.id")) & better).select(F.col("a.scope").alias("scope"), F.col("a.id").alias("winner"), F.col("b.id").alias("loser"))


def token_array(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))


def token_overlap(queries: DataFrame, docs: DataFrame) -> DataFrame:
    """(scope, id, overlap): distinct query tokens that the document holds, where there are any. An equi-join on tokens."""
    q = queries.select("scope", F.explode(F.array_distinct(token_array(F.col("query")))).alias("t"))
    d = docs.select("id", F.explode(F.array_distinct(token_array(F.col("payload")))).alias("t"))
    return d.join(q, "t").groupBy("scope", "id").agg(F.count("*").alias("overlap"))


def bm25(queries: DataFrame, docs: DataFrame, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """(scope, id, bm25)."""
    counted = docs.select("id", F.explode(token_array(F.col("payload"))).alias("t")).groupBy("id", "t").agg(F.count("*").alias("tf"))
    size = counted.groupBy("id").agg(F.sum("tf").alias("len"))
    stats = size.agg(F.avg("len").alias("mean"), F.count("*").alias("n"))
    df = counted.groupBy("t").agg(F.count("*").alias("df"))
    q = queries.select("scope", F.explode(F.array_distinct(token_array(F.col("query")))).alias("t"))
    x = q.join(df, "t").join(counted, "t").join(size, "id").crossJoin(F.broadcast(stats))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    return x.groupBy("scope", "id").agg(F.sum(idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.col("mean")))).alias("bm25"))


def tfidf_cosine(queries: DataFrame, docs: DataFrame, dims: int = 4096) -> DataFrame:
    """(scope, id, cosine) over hashed term weights."""
    slot = F.pmod(F.xxhash64("t"), F.lit(dims))
    d = docs.select("id", F.explode(token_array(F.col("payload"))).alias("t")).groupBy("id", slot.alias("s")).agg(F.count("*").alias("tf"))
    n = docs.agg(F.count("*").alias("n"))
    idf = d.groupBy("s").agg(F.count("*").alias("df")).crossJoin(F.broadcast(n)).select("s", F.log((1 + F.col("n")) / (1 + F.col("df"))).alias("idf"))
    weighed = d.join(idf, "s").withColumn("w", F.col("tf") * F.col("idf"))
    norm = weighed.groupBy("id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    q = queries.select("scope", F.explode(token_array(F.col("query"))).alias("t")).groupBy("scope", slot.alias("s")).agg(F.count("*").alias("qf")).join(idf, "s").withColumn("qw", F.col("qf") * F.col("idf")).select("scope", "s", "qw")
    qnorm = q.groupBy("scope").agg(F.sqrt(F.sum(F.col("qw") * F.col("qw"))).alias("qnorm"))
    dot = weighed.join(q, "s").groupBy("scope", "id").agg(F.sum(F.col("w") * F.col("qw")).alias("dot"))
    return dot.join(norm, "id").join(qnorm, "scope").select("scope", "id", F.when(F.col("norm") * F.col("qnorm") > 0, F.col("dot") / (F.col("norm") * F.col("qnorm"))).otherwise(0.0).alias("cosine"))


def reciprocal_rank_fusion(parts: list[DataFrame], n: int, c: int = 60) -> DataFrame:
    """(scope, id, score): the best n of each scope by summed 1 / (c + rank) over all ranks. parts: (scope, id, value)."""
    total = None
    for x in parts:
        w = W.partitionBy("scope").orderBy(F.desc(F.round("value", 9)), "id")
        one = x.withColumn("r", F.row_number().over(w)).select("scope", "id", (1 / (c + F.col("r"))).alias("s"))
        total = one if total is None else total.unionByName(one)
    fused = total.groupBy("scope", "id").agg(F.round(F.sum("s"), 9).alias("score"))
    w = W.partitionBy("scope").orderBy(F.desc("score"), "id")
    return fused.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= n).drop("r")


def ensemble_retrieve(queries: DataFrame, docs: DataFrame, n: int = 50) -> DataFrame:
    """(scope, id, score): token overlap, BM25 and hashed term cosine, fused over all their ranks."""
    return fused_best(queries, docs, n)


def ensemble_pairs(queries: DataFrame, docs: DataFrame, n: int = 50) -> DataFrame:
    """The same by a row for each pair of query and document: what ``ensemble_retrieve`` is held against."""
    return reciprocal_rank_fusion([
        token_overlap(queries, docs).select("scope", "id", F.col("overlap").cast("double").alias("value")),
        bm25(queries, docs).select("scope", "id", F.col("bm25").alias("value")),
        tfidf_cosine(queries, docs).select("scope", "id", F.col("cosine").alias("value")),
    ], n)


def judge_gold(queries: DataFrame, docs: DataFrame, pool: int = 50, top: int = 10) -> DataFrame:
    """(scope, id, gold_rank): the ensemble's pool ranked by Elo over all pairs, the first ``top``."""
    pooled = materialise(ensemble_retrieve(queries, docs, pool), "pool")
    return elo_rank(all_pairs(pooled)).filter(F.col("gold_rank") <= top).select("scope", "id", "gold_rank")


#: Words of a run that a passage and a document must share.
RUN = 5
_RUNS = re.compile("[A-Za-z0-9]+")
#: Every byte but letters and digits as a blank: what lies between are the runs of a text in UTF-8.
_BYTES = bytes(c if chr(c).isascii() and chr(c).isalnum() else 32 for c in range(256))


def sparse_gold(queries: DataFrame, docs: DataFrame) -> DataFrame:
    """(scope, id, rel): documents that hold a query's passage. Texts are read once and not moved; queries go to every task whole.

    A document that holds a passage holds the run of words after the passage's first word (which, like its last, may be
    cut from a longer one), so passages of RUN + 2 words or more are looked for only where that run stands; shorter
    passages, a few words each, are looked for in every document.
    """
    short: list[tuple[int, str]] = []
    long: dict[tuple[bytes, ...], list[tuple[int, str]]] = {}
    for r in queries.filter(F.length("query") > 0).select("scope", "query").collect():
        own = _RUNS.findall(r["query"])
        (short if len(own) < RUN + 2 else long.setdefault(tuple(x.encode() for x in own[1 : 1 + RUN]), [])).append((r["scope"], r["query"]))

    first = {key[0] for key in long}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                if (text := text.as_py()) is not None:
                    own = text.encode().translate(_BYTES).split()
                    keys = {key for i, word in enumerate(own) if word in first and (key := tuple(own[i : i + RUN])) in long}
                    near = [x for key in keys for x in long[key]]
                    found += [(scope, i) for scope, query in (*near, *short) if query in text]
            yield pa.RecordBatch.from_arrays([pa.array([x[j] for x in found], pa.int64()) for j in (0, 1)], ["scope", "id"])

    bound_batches(docs.sparkSession)
    texts = docs.select(F.col("id").cast("long").alias("id"), F.col("payload").cast("string").alias("payload"))
    return texts.mapInArrow(run, "scope bigint, id bigint").withColumn("rel", F.lit(1))
