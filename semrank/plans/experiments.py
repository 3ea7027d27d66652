"""The experiment workloads on the given tables: which method wins, and how each measure moves with each parameter.

Corpus: documents; queries: benchmark passages that some document holds, at most 25. A document's true relevance to a
query is the number of distinct query tokens it holds (score), so rankers with and without noise need no text.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..operators import baselines, retrieval, topk
from ..operators.kernel import Ranked
from ..operators.rankers import ColumnRanker, NoisyRanker, PairNoiseByListSize, PointScorer, PositionBiasedRanker, Ranker
from ..schema import RankParams
from ..sources.tables import items_of, load, materialise
from . import metrics, simulate

SEED, QUERIES, K = 42, 25, 10
#: Noise of the fine-tuned ranker, of general models, and the proxy's.
FINE, GENERAL = 0.3, 3.0
#: Runs of an experiment at a time.
TOGETHER = 3


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("text").alias("payload"))


def queries(spark: SparkSession, sf_dir: str, n: int = QUERIES) -> DataFrame:
    """The first n benchmark items that some document holds."""
    bench = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("scope"), F.col("text").alias("query"))
    held = baselines.sparse_gold(bench, corpus(spark, sf_dir)).select("scope").distinct()
    return materialise(bench.join(held, "scope", "left_semi").orderBy("scope").limit(n), "queries")  # few rows, read several times


def first_docs(docs: DataFrame, n: int) -> DataFrame:
    """n documents in the order of a hash."""
    return docs.orderBy(F.md5(F.col("id").cast("string").cast("binary"))).limit(n)


def claim_items(spark: SparkSession, sf_dir: str, n_queries: int = QUERIES, n_docs: int | None = None, asks: DataFrame | None = None, docs: DataFrame | None = None) -> DataFrame:
    """items: every document for every query with its true relevance; proxy: relevance seen through a rough lens. asks, docs: the queries and the corpus, where known."""
    docs = corpus(spark, sf_dir) if docs is None else docs
    if n_docs:
        docs = first_docs(docs, n_docs)
    score = F.col("overlap").cast("double")
    rough = score + 3 * (F.conv(F.substring(F.md5(F.concat_ws(":", "scope", "id").cast("binary")), 1, 6), 16, 10).cast("double") / 16777216 - 0.5)
    return materialise(retrieval.overlaps(queries(spark, sf_dir, n_queries) if asks is None else asks, docs).select("scope", "id", F.lit(None).cast("string").alias("payload"), score.alias("score"), rough.alias("proxy")), "claims")


def gold_of(items: DataFrame, k: int = K) -> DataFrame:
    """(scope, id, rel): the true top k, graded by place."""
    return topk.exact_topk(items, k).select("scope", "id", (F.lit(k + 1) - F.col("rank")).alias("rel"))


def fine(sigma: float = FINE) -> Ranker:
    return NoisyRanker(ColumnRanker(), sigma, SEED)


def general(sigma: float = GENERAL) -> Ranker:
    return PositionBiasedRanker(ColumnRanker(), sigma, SEED, beta=1.0)


def measured(label: str, done: Ranked, items: DataFrame, k: int = K, ordered: bool = True, gold: DataFrame | None = None) -> DataFrame:
    """(label, calls, recall, ndcg): means over queries. gold: (scope, id, rel), the true top k if not given."""
    gold = gold_of(items, k) if gold is None else gold
    rows = materialise(done.rows.filter(F.col("rank").isNull() | (F.col("rank") <= k)), "rows")  # what the measures look at
    recall = metrics.recall_at_k(rows, gold, k).agg(F.avg("recall").alias("recall"))
    ndcg = metrics.ndcg_at_k(rows, gold, k).agg(F.avg("ndcg").alias("ndcg")) if ordered else recall.select(F.lit(None).cast("double").alias("ndcg"))
    n = items.select("scope").distinct().count()
    calls = done.calls.agg((F.count("*") / n).alias("calls"))
    return materialise(recall.crossJoin(ndcg).crossJoin(calls).select(F.lit(label).alias("label"), "calls", "recall", "ndcg"), "measured")


def _all(parts: Iterable[DataFrame]) -> DataFrame:
    out = None
    for x in parts:
        out = x if out is None else out.unionByName(x)
    return out


def _together(runs: Iterable[Callable[[], DataFrame]]) -> DataFrame:
    """The rows of runs that don't need one another, TOGETHER of them at a time: many of a run's jobs are too small for a cluster."""
    with ThreadPoolExecutor(TOGETHER) as pool:
        return _all(pool.map(lambda run: run(), runs))


def four_plans(items: DataFrame, ranker: Ranker, survivors: Iterable[int] = (1, 5, 10, 15), params: RankParams | None = None, gold: DataFrame | None = None) -> DataFrame:
    """Every plan with and without the filter: calls, recall and NDCG."""
    params = params or RankParams.default()
    gold = materialise(gold_of(items), "gold") if gold is None else gold
    parts = []
    for s in (0, *survivors):
        kept = topk.bin_filter(items, ranker, params.but(survivors=s), SEED) if s else None
        own = materialise(kept.rows, "kept") if kept else items
        for agg in ("tournament", "pivot"):
            done = topk.tournament(own, K, ranker, params, SEED) if agg == "tournament" else topk.pivot_topk(own, K, ranker, params, SEED)
            calls = done.calls.unionByName(kept.calls) if kept else done.calls
            parts.append(measured(f"{agg} S={s}" if s else agg, Ranked(done.rows, calls), items, gold=gold))
    return _all(parts)


def method_table(items: DataFrame, gold: DataFrame | None = None) -> DataFrame:
    """Ours and the baselines on one workload. What a ranker is worth is an input here: the noise of FINE and GENERAL, and half of FINE for pairs."""
    p = RankParams.default()
    point = PointScorer(ColumnRanker(), 5000, 0.02, SEED)
    gold = materialise(gold_of(items), "gold") if gold is None else gold
    runs = {
        "tournament": lambda: topk.tournament(items, K, fine(), p, SEED),
        "pivot": lambda: topk.pivot_topk(items, K, fine(), p, SEED),
        "tournament, general model": lambda: topk.tournament(items, K, general(), p, SEED),
        "pivot, general model": lambda: topk.pivot_topk(items, K, general(), p, SEED),
        "pairwise_prior": lambda: baselines.pairwise_prior(items, K, NoisyRanker(ColumnRanker(), FINE / 2, SEED)),
        "pairwise_list": lambda: baselines.pairwise_list(items, K, fine()),
        "pointwise": lambda: baselines.pointwise_topk(items, K, point),
    }
    return _together((lambda label=label, run=run: measured(label, run(), items, gold=gold)) for label, run in runs.items())


def pareto_methods(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The undominated methods of the workload by calls and NDCG, the four plans among them."""
    items = claim_items(spark, sf_dir)
    gold = materialise(gold_of(items), "gold")
    table = method_table(items, gold).unionByName(four_plans(items, fine(), (1,), gold=gold).filter("label like '%S=1'"))
    return metrics.pareto(materialise(table, "methods"), "calls", "ndcg")


def review_items(spark: SparkSession, sf_dir: str, kind: str = "documents", n: int = 256) -> DataFrame:
    """A full sort of n texts by how many tokens of one query they hold: documents or user turns of conversations."""
    if kind == "documents":
        x = load(spark, sf_dir, "documents").filter("lang = 'en'").orderBy("doc_id").limit(n).select(F.col("doc_id").alias("id"), "text")
    else:
        x = load(spark, sf_dir, "conversations").filter("role = 'user'").orderBy("conv_id", "turn").limit(n).select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    tokens = F.array_distinct(baselines.token_array(F.col("text")))
    return items_of(x, "id", F.size(tokens).cast("double"), proxy=F.length("text").cast("double"))


def review_sort(spark: SparkSession, sf_dir: str, kind: str = "documents") -> DataFrame:
    """(label, calls, spearman): listwise sorts against pairwise and pointwise."""
    items = materialise(review_items(spark, sf_dir, kind), "reviews")
    n = items.count()
    truth = items.select("scope", "id", (-F.col("score")).alias("value"))
    scale = 8.0
    runs = {
        "pivot_sort": topk.sort(items, fine(scale), RankParams(pivots=6), SEED),
        "tournament": topk.tournament(items, n, fine(scale), RankParams(), SEED),
        "pairwise": topk.sort(items, fine(scale), RankParams(list_size=2, pivots=1), SEED),
        "pointwise": baselines.pointwise_topk(items, n, PointScorer(ColumnRanker(), 5, 0.02, SEED)),
    }
    return _all(metrics.spearman(done.rows.select("scope", "id", F.col("rank").cast("double").alias("value")), truth).crossJoin(done.calls.agg(F.count("*").alias("calls"))).select(F.lit(label).alias("label"), "calls", "spearman") for label, done in runs.items())


def sweep_select(items: DataFrame, name: str, values: list, of, ranker: Ranker, k_of=lambda v: K) -> DataFrame:
    """(value, calls, recall) of select over one parameter. of(value): its RankParams."""
    golds = {k: materialise(gold_of(items, k), "gold") for k in {k_of(v) for v in values}}

    def run(v) -> DataFrame:
        got = measured(str(v), topk.select(items, k_of(v), ranker, of(v), SEED), items, k_of(v), False, golds[k_of(v)])
        return got.select(F.lit(name).alias("parameter"), F.lit(float(v)).alias("value"), "calls", "recall")

    return _together((lambda v=v: run(v)) for v in values)


def sweep_list_size(items: DataFrame) -> DataFrame:
    """Calls, and latency as calls times (1 + list size / 20): prompts cost more as they grow. Quality falls past 64."""
    got = sweep_select(items, "list_size", [2, 5, 10, 20, 32, 64, 96, 128], lambda v: RankParams(list_size=v, pivots=1), PairNoiseByListSize(ColumnRanker(), FINE, SEED))
    return got.withColumn("latency", F.col("calls") * (0.2 + F.col("value") / 20))


def sweep_k(items: DataFrame) -> DataFrame:
    return sweep_select(items, "k", [1, 5, 10, 20, 50], lambda v: RankParams(pivots=4), fine(), lambda v: v)


def sweep_p(items: DataFrame) -> DataFrame:
    return sweep_select(items, "pivots", [1, 2, 4, 6, 8, 12, 16], lambda v: RankParams(pivots=v), fine())


def sweep_sort(spark: SparkSession, sf_dir: str) -> DataFrame:
    """NDCG of a full sort against the number of documents (flat) and the list size (falling)."""
    out, asks = [], queries(spark, sf_dir)
    docs = materialise(first_docs(corpus(spark, sf_dir), 200), "docs")
    for n in (50, 100, 200):
        items = claim_items(spark, sf_dir, n_docs=n, asks=asks, docs=docs)
        out.append(measured("n", topk.sort(items, fine(), RankParams(pivots=6), SEED), items).withColumn("value", F.lit(float(n))))
    items = claim_items(spark, sf_dir, asks=asks)
    gold = materialise(gold_of(items), "gold")

    def run(size: int) -> DataFrame:
        done = topk.sort(items, PairNoiseByListSize(ColumnRanker(), FINE, SEED, knee=16), RankParams(list_size=size, pivots=min(6, size - 2)), SEED)
        return measured("list_size", done, items, gold=gold).withColumn("value", F.lit(float(size)))

    out.append(_together((lambda size=size: run(size)) for size in (5, 20, 64, 128)))
    return _all(out).select(F.col("label").alias("parameter"), "value", "calls", "ndcg")


def embedding_items(spark: SparkSession, sf_dir: str, n_queries: int = QUERIES) -> DataFrame:
    """Vectors by cosine with the first n as queries; the proxy sees the first 16 of their dimensions."""
    v = load(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    q = v.filter(F.col("vec_id") < n_queries).select(F.col("vec_id").alias("scope"), F.col("e").alias("q"))
    both = v.crossJoin(F.broadcast(q))
    return materialise(both.select("scope", F.col("vec_id").alias("id"), F.lit(None).cast("string").alias("payload"), cosine("e", "q").alias("score"), cosine(F.slice("e", 1, 16), F.slice("q", 1, 16)).alias("proxy")), "vectors")


def cosine(a, b):
    """Cosine of two arrays of doubles, rounded to six places."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, p: s + p)
    return F.round(dot(a, b) / F.sqrt(dot(a, a) * dot(b, b)), 6)


def proxy_pivots(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(label, mean, most): calls of select with random and with proxy pivots."""
    items = embedding_items(spark, sf_dir)
    out = []
    for mode in ("random", "proxy"):
        calls = topk.select(items, K, ColumnRanker(), RankParams(pivots=4, pivot_mode=mode), SEED).calls.groupBy("scope").agg(F.count("*").alias("calls"))
        out.append(calls.agg(F.avg("calls").alias("mean"), F.max("calls").alias("most")).select(F.lit(mode).alias("label"), "mean", "most"))
    return _all(out)


def pivot_groups(items: DataFrame) -> DataFrame:
    """(p, p_prime, early_stop, calls) of select."""

    def run(p: int, group: int, stop: bool) -> DataFrame:
        calls = topk.select(items, K, ColumnRanker(), RankParams(pivots=p, pivot_group=group, early_stop=stop), SEED).calls
        return calls.groupBy("scope").agg(F.count("*").alias("c")).agg(F.avg("c").alias("calls")).select(F.lit(p).alias("p"), F.lit(group).alias("p_prime"), F.lit(stop).alias("early_stop"), "calls")

    return _together((lambda x=(p, *x): run(*x)) for p in (4, 8, 16) for x in ((p, False), (2, False), (2, True)))


def refinement(items: DataFrame) -> DataFrame:
    """The first ten again by pairs, on or off, with a ranker that is better on short lists."""
    ranker = PairNoiseByListSize(ColumnRanker(), FINE, SEED, knee=2)
    return _all(measured(label, topk.pivot_topk(items, K, ranker, RankParams.default(), SEED, refine=m), items) for label, m in (("plain", 0), ("refined", 10)))


def filter_recall(items: DataFrame, survivors: Iterable[int], ks: Iterable[int], size: int = 20) -> DataFrame:
    """(s, k, recall) measured from one binning: a document survives if its place in its bin is at most S."""
    from ..operators.binning import assign_bins

    w = W.partitionBy("scope", "bin").orderBy(F.desc("score"), "id")
    placed = assign_bins(items, size, SEED, 0).withColumn("place", F.row_number().over(w)).select("scope", "id", "place")
    ranked = topk.exact_topk(items, max(ks)).join(placed, ["scope", "id"])
    cells = F.array(*(F.struct(F.lit(s).alias("s"), F.lit(k).alias("k")) for s in survivors for k in ks))
    return ranked.withColumn("c", F.explode(cells)).filter("rank <= c.k").groupBy("scope", F.col("c.s").alias("s"), F.col("c.k").alias("k")).agg((F.sum(F.when(F.col("place") <= F.col("c.s"), 1).otherwise(0)) / F.count("*")).alias("recall"))


def tuning_gain(spark: SparkSession, trials: int = simulate.TRIALS) -> DataFrame:
    """(algo, worst, best, gain): calls saved by the best number of pivots against the others tried."""
    grids = {"select": [{"n": 1000, "k": 10, "size": 20, "p": p} for p in (1, 2, 4, 6, 8)], "sort": [{"n": 1000, "size": 20, "p": p} for p in (1, 2, 4, 6, 8, 12)]}
    return _all(simulate.simulate_grid(spark, a, g, trials).agg(F.max("value").alias("worst"), F.min("value").alias("best")).select(F.lit(a).alias("algo"), "worst", "best", (1 - F.col("best") / F.col("worst")).alias("gain")) for a, g in grids.items())


def reduced_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Only each query's 100 most relevant documents: all methods again."""
    items = claim_items(spark, sf_dir)
    w = W.partitionBy("scope").orderBy(F.desc("proxy"), "id")
    near = materialise(items.withColumn("r", F.row_number().over(w)).filter("r <= 100").drop("r"), "near")
    return method_table(near)


def judge_workload(spark: SparkSession, sf_dir: str, n_queries: int = QUERIES) -> DataFrame:
    """Against judge labels: a pooled, Elo-ranked gold of ten a query."""
    q, docs = queries(spark, sf_dir, n_queries), corpus(spark, sf_dir)
    gold = materialise(baselines.judge_gold(q, docs), "judge")
    items = claim_items(spark, sf_dir, n_queries)
    qrels = gold.select("scope", "id", (F.lit(11) - F.col("gold_rank")).alias("rel"))
    done = topk.pivot_topk(items, K, fine(), RankParams.default(), SEED)
    return metrics.recall_at_k(done.rows, gold, K).join(metrics.ndcg_at_k(done.rows, qrels, K), "scope")


def sparse_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All methods against the few documents that hold a query's passage."""
    gold = materialise(baselines.sparse_gold(queries(spark, sf_dir), corpus(spark, sf_dir)), "sparse")
    return method_table(claim_items(spark, sf_dir), gold)


def judge_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All methods against the ten documents that the ensemble and Elo ratings put first."""
    gold = materialise(baselines.judge_gold(queries(spark, sf_dir), corpus(spark, sf_dir)), "judge")
    return method_table(claim_items(spark, sf_dir), gold.select("scope", "id", (F.lit(11) - F.col("gold_rank")).alias("rel")))
