"""Scopes held as arrays: the same results and ledgers as call by call."""

import pytest
from pyspark.sql import functions as F

from semrank.operators import columns, topk
from semrank.operators.rankers import ColumnRanker, NoisyRanker, PairNoiseByListSize, PositionBiasedRanker
from semrank.schema import RankParams
from semrank.sources.tables import items_of

RANKERS = {
    "noisy": NoisyRanker(ColumnRanker(), 20.0, 3),
    "biased": PositionBiasedRanker(ColumnRanker(), 30.0, 3, beta=2.0),
    "long lists": PairNoiseByListSize(ColumnRanker(), 10.0, 3, knee=4),
}
STOP = RankParams(pivots=16, pivot_group=2, early_stop=True)
RUNS = {
    "select": lambda x, r: topk.select(x, 12, r, RankParams(pivots=4), 7),
    "select, lists of two": lambda x, r: topk.select(x, 12, r, RankParams(list_size=2, pivots=1), 7),
    "select with stop": lambda x, r: topk.select(x, 30, r, STOP, 7),
    "select, unlike groups": lambda x, r: topk.select(x, 30, r, RankParams(list_size=9, pivots=5, pivot_group=2, pivot_mode="proxy", slot_order="input"), 7),
    "pivot": lambda x, r: topk.pivot_topk(x, 12, r, STOP, 7, refine=5, sort_pivots=4),
    "pairs": lambda x, r: topk.pivot_topk(x, 12, r, RankParams(list_size=2, pivots=1, pivot_mode="proxy"), 7),
    "sort": lambda x, r: topk.sort(x, r, RankParams(list_size=5, pivots=3), 7),
    "sort, unlike groups": lambda x, r: topk.sort(x, r, RankParams(list_size=12, pivots=5, pivot_group=2), 7),
    "tournament": lambda x, r: topk.tournament(x, 6, r, RankParams(list_size=8, pivots=1), 7),
    "filter": lambda x, r: topk.bin_filter(x, r, RankParams(list_size=8, pivots=1, survivors=3), 7, rounds=2),
}


@pytest.fixture(scope="module")
def items(spark):
    """Scopes of 700, 150, 21, 20, 1 documents; ties, nulls, texts of different lengths."""
    rows = spark.range(892).select("id", F.expr("CASE WHEN id < 700 THEN 0 WHEN id < 850 THEN 1 WHEN id < 871 THEN 2 WHEN id < 891 THEN 3 ELSE 4 END").alias("s"))
    score = F.when(F.col("id") % 97 == 0, F.lit(None)).when(F.col("id") % 89 == 0, F.lit(float("nan"))).otherwise((F.xxhash64("id") % 400).cast("double"))
    return items_of(rows, "id", score, F.repeat(F.lit("x"), (F.col("id") % 7).cast("int")), F.when(F.col("id") % 50 > 0, (F.xxhash64("id") % 90).cast("double")), F.col("s")).cache()


def outcome(done):
    return sorted(map(tuple, done.rows.select(*(c for c in ("scope", "rank", "id") if c in done.rows.columns)).collect()), key=repr), sorted(map(tuple, done.calls.drop("run_id").collect()))


@pytest.mark.parametrize("ranker", RANKERS)
@pytest.mark.parametrize("run", RUNS)
def test_arrays_are_as_call_by_call(items, run, ranker, monkeypatch):
    monkeypatch.setattr(columns, "BATCH", 300)  # ledgers of many batches
    asked = []
    whole = topk.run_columns
    monkeypatch.setattr(topk, "run_columns", lambda *a, **b: asked.append(a) or whole(*a, **b))
    got = outcome(RUNS[run](items, RANKERS[ranker]))
    assert asked
    monkeypatch.setattr(columns, "columnar", lambda ranker: False)
    monkeypatch.setattr(topk, "run_columns", None)
    want = outcome(RUNS[run](items, RANKERS[ranker]))
    assert got[0] == want[0]
    assert got[1] == want[1]


def test_overlaps_of_odd_texts(spark):
    """Words are those of the pattern, whatever letters lie between them."""
    from semrank.operators import retrieval

    texts = ["", None, "Abc-ABC kelvin", "İstanbul Kelvin", "naïve cafés", "xß1y z\U0001f600a abc"]
    docs = spark.createDataFrame(list(enumerate(texts)), "id bigint, payload string")
    asked = {7: "abc kelvin i stanbul na ve", 8: "caf s x y z a"}
    got = retrieval.overlaps(spark.createDataFrame(list(asked.items()), "scope bigint, query string"), docs).collect()
    assert {(r["scope"], r["id"]): r["overlap"] for r in got} == {(s, i): len(set(retrieval.words(q)) & set(retrieval.words(t))) for s, q in asked.items() for i, t in enumerate(texts)}


def test_sort_sweep_looks_for_its_queries_once(spark, sf_dir, monkeypatch):
    from semrank.plans import experiments

    asked, whole, arrays = [], experiments.queries, []
    monkeypatch.setattr(experiments, "queries", lambda *a: asked.append(a) or whole(*a))
    run = topk.run_columns
    monkeypatch.setattr(topk, "run_columns", lambda items, algo, *a, **b: arrays.append(algo) or run(items, algo, *a, **b))
    got = experiments.sweep_sort(spark, sf_dir).collect()
    assert [(r["parameter"], r["value"]) for r in got] == [("n", 50), ("n", 100), ("n", 200), ("list_size", 5), ("list_size", 20), ("list_size", 64), ("list_size", 128)]
    assert len(asked) == 1 and arrays == ["sort"] * 7


def swept(run, monkeypatch):
    """Rows of an experiment, which scopes were finished as arrays, and rows without that."""
    from semrank.plans import experiments

    asked, whole = [], topk.run_columns
    monkeypatch.setattr(topk, "run_columns", lambda items, algo, *a, **b: asked.append(algo) or whole(items, algo, *a, **b))
    got = run(experiments).collect()
    monkeypatch.setattr(columns, "columnar", lambda ranker: False)
    return sorted(map(tuple, got)), sorted(asked), sorted(map(tuple, run(experiments).collect()))


def test_list_sizes_as_call_by_call(items, monkeypatch):
    got, asked, want = swept(lambda e: e.sweep_list_size(items.filter("scope in (1, 2)")), monkeypatch)
    assert got == want and asked == ["select"] * 8


def test_pareto_finds_its_gold_once(spark, sf_dir, monkeypatch):
    from semrank.plans import experiments

    asked, whole = [], experiments.gold_of
    monkeypatch.setattr(experiments, "gold_of", lambda *a: asked.append(a) or whole(*a))
    monkeypatch.setattr(experiments, "QUERIES", 3)
    assert experiments.pareto_methods(spark, sf_dir).count() and len(asked) == 1


def test_points_as_one_by_one():
    from semrank.operators.rankers import ListRequest, PointScorer

    scorer = PointScorer(ColumnRanker(), 5000, 0.1, 3)
    scores = [None if i % 9 == 0 else float(i % 40 - 5) for i in range(500)]
    assert scorer.responses(list(range(500)), scores) == [scorer.respond(ListRequest("c", [i], [None], [s])) for i, s in enumerate(scores)]
