"""Where calls are made says nothing about which: results and ledgers are the same for any tail."""

import pytest
from pyspark.sql import functions as F

from semrank.operators import topk
from semrank.operators.rankers import BrokenRanker, ColumnRanker, ContradictingRanker, LexicalRanker, NoisyRanker, PairNoiseByListSize, PositionBiasedRanker
from semrank.schema import RankParams
from semrank.sources.tables import items_of

RANKERS = {
    "perfect": ColumnRanker(),
    "noisy": NoisyRanker(ColumnRanker(), 20.0, 3),
    "biased": PositionBiasedRanker(ColumnRanker(), 30.0, 3, beta=2.0),
    "long lists": PairNoiseByListSize(ColumnRanker(), 10.0, 3, knee=4),
    "contradicting": ContradictingRanker(ColumnRanker(), 0.4, 3),
    "broken": BrokenRanker(ColumnRanker()),
}


@pytest.fixture(scope="module")
def items(spark):
    """Scopes of 300, 150, 21, 20, 1 documents; ties, nulls, texts of different lengths."""
    rows = spark.range(492).select("id", F.expr("CASE WHEN id < 300 THEN 0 WHEN id < 450 THEN 1 WHEN id < 471 THEN 2 WHEN id < 491 THEN 3 ELSE 4 END").alias("s"))
    score = F.when(F.col("id") % 97 == 0, F.lit(None)).otherwise((F.xxhash64("id") % 400).cast("double"))
    return items_of(rows, "id", score, F.repeat(F.lit("x"), (F.col("id") % 7).cast("int")), F.when(F.col("id") % 50 > 0, (F.xxhash64("id") % 90).cast("double")), F.col("s")).cache()


def outcome(done):
    calls = done.calls.drop("run_id").collect()
    return sorted(map(tuple, done.rows.select("scope", "rank", "id").collect()), key=repr), sorted(map(tuple, calls)), len(calls)


def same(run, tails=(60, 10**9)):
    got = [outcome(run(t)) for t in tails]
    for rows, calls, n in got[1:]:
        assert rows == got[0][0]
        assert calls == got[0][1]
    names = [c[3] for c in got[0][1]]
    assert len(set(names)) == len(names) > 0
    return got[0]


@pytest.mark.parametrize("name", RANKERS)
def test_select_and_sort(items, name):
    same(lambda t: topk.pivot_topk(items, 12, RANKERS[name], RankParams(pivots=6, pivot_group=3, early_stop=True), 7, tail=t, refine=5, sort_pivots=4), (0, 10**9) if name == "noisy" else (160, 10**9))


@pytest.mark.parametrize("params", [RankParams(pivots=6, pivot_group=4, early_stop=True, slot_order="input"), RankParams(list_size=9, pivots=3, pivot_group=2, pivot_mode="proxy")])
def test_select_over_parameters(items, params):
    same(lambda t: topk.select(items, 25, RANKERS["noisy"], params, 9, tail=t), (120, 10**9))


@pytest.mark.parametrize("params", [RankParams(pivots=4, pivot_mode="proxy"), RankParams(pivots=5, pivot_group=2)])
def test_full_sort(items, params):
    rows, _, _ = same(lambda t: topk.sort(items, RANKERS["noisy"], params, 5, tail=t), (120, 10**9))
    assert len(rows) == 492 and {r[1] for r in rows if r[0] == 0} == set(range(1, 301))


@pytest.mark.parametrize("name", ["noisy"])
def test_tournament(items, name):
    same(lambda t: topk.tournament(items, 6, RANKERS[name], RankParams(list_size=8, pivots=1), 3, tail=t), (60, 10**9))


def test_votes(items):
    one = items.filter("scope > 0")
    same(lambda t: topk.pivot_topk(one, 8, RANKERS["noisy"], RankParams(pivots=3), 1, tail=t, votes=3), (100, 10**9))
    calls = topk.tournament(one, 3, RANKERS["noisy"], RankParams(), 1, tail=100, votes=2).calls.drop("run_id").collect()
    assert len(calls) % 2 == 0 and all("#" in c[3] for c in calls)


def test_bytes_bound_the_tail(items, monkeypatch):
    whole = outcome(topk.select(items, 30, RANKERS["noisy"]))
    monkeypatch.setattr(topk, "TAIL_BYTES", 600)
    assert outcome(topk.select(items, 30, RANKERS["noisy"])) == whole


def test_large_k(items):
    """More winners than a list holds, with a tail that holds only groups of the documents; a sort of more than the tail."""
    for done in (topk.tournament(items, 25, ColumnRanker(), tail=120), topk.pivot_topk(items, 200, ColumnRanker(), tail=100)):
        k = 25 if done.rows.filter("scope = 0").count() == 25 else 200
        want = topk.exact_topk(items.withColumn("score", F.coalesce("score", F.lit(-1e9))), k)
        assert want.exceptAll(done.rows.select("scope", "rank", "id")).count() == 0 == done.rows.count() - want.count()
        assert done.calls.count() == done.calls.select("call_id").distinct().count() or k == 25
    with pytest.raises(ValueError, match="winners"):
        topk.tournament(items, 100, ColumnRanker(), tail=120)


def test_tournament_for_all_documents(items):
    """More documents than a task holds: segments with a tournament each; a scope that fits is one tournament."""
    full = items.withColumn("score", F.coalesce("score", F.lit(-1e9)))
    done = topk.tournament_sort(full, ColumnRanker(), tail=60)
    assert topk.exact_topk(full, 1000).exceptAll(done.rows.select("scope", "rank", "id")).count() == 0 and done.rows.count() == 492
    assert done.calls.count() == done.calls.select("call_id").distinct().count()
    plain, whole = topk.tournament(items, 492, RANKERS["noisy"], RankParams(), 3), topk.tournament_sort(items, RANKERS["noisy"], RankParams(), 3)
    assert outcome(plain) == outcome(whole)


def test_every_query_without_a_row_for_each_pair(spark, monkeypatch):
    """Chunks and tasks with fewer and more documents than k; no intermediate result has as many rows as there are pairs."""
    words = F.concat_ws(" ", *(F.when(F.xxhash64("id", F.lit(w)) % 3 == 0, F.lit(w)) for w in ("cat", "dog", "bird", "fish", "cow")))
    docs = spark.range(900).repartition(4).select("id", F.when(F.col("id") % 50 > 0, words).alias("payload"), F.lit(None).cast("double").alias("score"), F.lit(None).cast("double").alias("proxy"))
    queries = spark.createDataFrame([(i, q) for i, q in enumerate(["cat dog", "bird fish cow", "horse", None, "cow cat bird dog fish"])], "scope long, query string")
    monkeypatch.setattr(topk, "CROSS", 100)
    rows, written = [], topk.materialise
    monkeypatch.setattr(topk, "materialise", lambda df, name="step": rows.append(out := written(df, name)) or out)
    done = topk.select_cross(docs, queries, 7, LexicalRanker())
    texts = {r["id"]: set((r["payload"] or "").split()) for r in docs.collect()}
    want = {(s, i) for s, q in queries.collect() for i in sorted(texts, key=lambda i: (-len(set((q or "").split()) & texts[i]), i))[:7]}
    assert {(r["scope"], r["id"]) for r in done.rows.collect()} == want and done.rows.count() == 35
    assert max(x.filter("id is not null").count() if "id" in x.columns else 0 for x in rows) < 900
    assert done.calls.count() == done.calls.select("call_id").distinct().count() > 5 * 900 / 20


def test_the_worst_by_any_ranker(items):
    full = items.withColumn("score", F.coalesce("score", F.lit(0.0)))
    up = full.withColumn("score", -F.col("score"))
    for ranker in (ColumnRanker(), NoisyRanker(ColumnRanker(), 0.0)):
        done = topk.pivot_topk(full, 5, ranker, ascending=True)
        got = {(r["scope"], r["rank"]): r["id"] for r in done.rows.collect()}
        scores = {r["id"]: r["score"] for r in full.collect()}
        want = {(r["scope"], r["rank"]): r["id"] for r in topk.exact_topk(up, 5).collect()}
        assert {k: scores[i] for k, i in got.items()} == {k: scores[i] for k, i in want.items()}


def test_lists_without_an_exchange_and_workers(items):
    """Bins inside partitions, through select, sort, filter and tournament; at most so many lists at a time."""
    one = items.filter("scope = 0").repartition(3)
    for mode in ("local",):
        p = RankParams(pivots=4, binning=mode, workers=2)
        kept = topk.bin_filter(one, NoisyRanker(ColumnRanker(), 0.0), p.but(survivors=12))
        assert kept.calls.agg(F.max("n_items")).first()[0] <= 20
        for done in (topk.pivot_topk(one, 12, NoisyRanker(ColumnRanker(), 0.0), p, tail=100), topk.tournament(one, 12, NoisyRanker(ColumnRanker(), 0.0), p, tail=100)):
            want = topk.exact_topk(one.withColumn("score", F.coalesce("score", F.lit(-1e9))), 12)
            assert want.exceptAll(done.rows.select("scope", "rank", "id")).count() == 0
            assert done.calls.agg(F.max("n_items")).first()[0] <= 20
