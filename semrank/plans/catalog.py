"""The library's registered queries: name, Spark form, and the same in DuckDB SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import api, sqlfront, udfs
from ..operators import baselines, binning, prompts, topk
from ..operators.kernel import lists_of, rank_lists
from ..operators.rankers import ColumnRanker, LexicalRanker, PointScorer
from ..schema import RankParams
from ..sources.tables import items_of, load, register_views, work_path
from ..streaming import topk as streams
from . import cost, experiments, metrics, planner, simulate

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
PERFECT = ColumnRanker()
#: The criterion of the text queries.
ASK = "the thing of that and is was by this with for from ering thand"


def query(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


def both(name: str, sql: str, duck: str | None = None, tables: tuple[str, ...] = ()) -> None:
    """A relational query: Spark SQL over views of the tables, and the same text (or ``duck``) for DuckDB."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        register_views(spark, sf_dir, [t for t in TABLES if t in sql] if not tables else tables)
        return spark.sql(sql)

    QUERIES[name] = run
    ORACLES[name] = duck or sql


TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


# ---- items -------------------------------------------------------------------------------------------------------


def order_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return items_of(load(spark, sf_dir, "orders"), "o_orderkey", F.col("o_totalprice"), proxy=F.col("o_totalprice"))


def line_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dearest line of each (order, line number): the pair isn't unique in the data, and ids must be."""
    x = load(spark, sf_dir, "lineitem").groupBy((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("id")).agg(F.max("l_extendedprice").alias("l_extendedprice"))
    return items_of(x, "id", F.col("l_extendedprice"), proxy=F.col("l_extendedprice"))


def text_items(spark: SparkSession, sf_dir: str, where: str = "true") -> DataFrame:
    return items_of(load(spark, sf_dir, "documents").filter(where), "doc_id", payload=F.col("text"))


def first_english(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").filter("lang = 'en'").orderBy("doc_id").limit(256)


def every_english(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").filter("lang = 'en'")


def lexical_items(df: DataFrame) -> DataFrame:
    """Lexical score as a column, and the text's length as a proxy for it."""
    ask = F.array_distinct(baselines.token_array(F.lit(ASK)))
    return items_of(df, "doc_id", F.size(F.array_intersect(ask, baselines.token_array(F.col("text")))).cast("double"), F.col("text"), F.length("text").cast("double"))


def scores_sql(q: str, text: str = "text") -> str:
    return f"len(list_intersect(list_distinct(regexp_extract_all(lower({q}), '[a-z]+')), list_distinct(regexp_extract_all(lower({text}), '[a-z]+'))))"


LEX = scores_sql(f"'{ASK}'")


def top_sql(table: str, key: str, score: str, k: int, where: str = "true", ranked: bool = True) -> str:
    inner = f"SELECT row_number() OVER (ORDER BY {score} DESC, {key}) AS rank, {key} AS id FROM {table} WHERE {where}"
    return f"SELECT {'rank, ' if ranked else ''}id FROM ({inner}) WHERE rank <= {k}"


def ordered(done) -> DataFrame:
    return done.rows.select("rank", "id")


def ids(done) -> DataFrame:
    return done.rows.select("id")


# ---- tournament, select, sort, filter, plans ---------------------------------------------------------------------

ORDERS10, ORDERS100 = top_sql("orders", "o_orderkey", "o_totalprice", 10), top_sql("orders", "o_orderkey", "o_totalprice", 100, ranked=False)
EN256 = "(SELECT * FROM documents WHERE lang = 'en' ORDER BY doc_id LIMIT 256)"
LINES10 = top_sql("(SELECT l_orderkey * 8 + l_linenumber AS line, max(l_extendedprice) AS l_extendedprice FROM lineitem GROUP BY 1)", "line", "l_extendedprice", 10)


@query(top_sql("orders", "o_orderkey", "o_totalprice", 20))
def exact_topk_orders(s, d):
    return topk.exact_topk(order_items(s, d), 20).select("rank", "id")


@query(ORDERS10)
def tournament_orders_top10(s, d):
    return ordered(topk.tournament(order_items(s, d), 10, PERFECT))


@query(top_sql("documents", "doc_id", LEX, 10))
def tournament_docs_lexical_top10(s, d):
    return ordered(topk.tournament(text_items(s, d), 10, LexicalRanker(ASK)))


@query(top_sql("orders", "o_orderkey", "o_totalprice", 1))
def tournament_top1(s, d):
    return ordered(topk.tournament(order_items(s, d), 1, PERFECT))


@query(top_sql("part", "p_partkey", "p_retailprice", 256, "p_partkey <= 256"))
def tournament_full_sort_parts(s, d):
    return ordered(topk.tournament(items_of(load(s, d, "part").filter("p_partkey <= 256"), "p_partkey", F.col("p_retailprice")), 256, PERFECT))


@query(LINES10)
def tournament_distributed_lineitem(s, d):
    return ordered(topk.tournament(line_items(s, d), 10, PERFECT, tail=5_000))


@query(ORDERS100)
def select_orders_top100_set(s, d):
    return ids(topk.select(order_items(s, d), 100, PERFECT, RankParams()))


@query(ORDERS100)
def select_random_p4(s, d):
    return ids(topk.select(order_items(s, d), 100, PERFECT, RankParams(pivots=4), seed=7))


@query(ORDERS100)
def select_p1(s, d):
    return ids(topk.select(order_items(s, d), 100, PERFECT, RankParams(pivots=1)))


@query(ORDERS100)
def select_p16_pp2_earlystop(s, d):
    return ids(topk.select(order_items(s, d), 100, PERFECT, RankParams.default()))


@query(ORDERS100)
def select_pprime_no_stop(s, d):
    return ids(topk.select(order_items(s, d), 100, PERFECT, RankParams(pivots=8, pivot_group=2)))


@query(ORDERS100)
def select_distributed(s, d):
    return ids(topk.select(order_items(s, d), 100, PERFECT, RankParams.default(), tail=2_000))


@query(top_sql("orders", "o_orderkey", "-o_totalprice", 20, ranked=False))
def select_bottom20(s, d):
    return ids(topk.select(order_items(s, d), 20, PERFECT, ascending=True))


_COS = "round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), (SELECT CAST(embedding AS DOUBLE[]) FROM embeddings WHERE vec_id = 0)), 6)"


@query(top_sql("embeddings", "vec_id", _COS, 10, ranked=False))
def select_proxy_embeddings(s, d):
    items = experiments.embedding_items(s, d, 1)
    return ids(topk.select(items, 10, PERFECT, RankParams(pivot_mode="proxy")))


_LANGS = "CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END"


@query(f"SELECT CAST({_LANGS} AS BIGINT) AS scope, doc_id AS id FROM (SELECT *, row_number() OVER (PARTITION BY {_LANGS} ORDER BY {LEX} DESC, doc_id) AS r FROM documents) WHERE r <= 10")
def select_per_lang_docs(s, d):
    items = text_items(s, d).drop("scope").join(load(s, d, "documents").select(F.col("doc_id").alias("id"), F.expr(_LANGS).cast("long").alias("scope")), "id")
    return topk.select(items, 10, LexicalRanker(ASK)).rows.select("scope", "id")


@query(f"SELECT item_id AS scope, doc_id AS id FROM (SELECT item_id, doc_id, row_number() OVER (PARTITION BY item_id ORDER BY {scores_sql('b.text', 'd.text')} DESC, doc_id) AS r FROM benchmark b, documents d) WHERE r <= 10")
def select_every_query(s, d):
    return topk.select_cross(text_items(s, d), _bench(s, d), 10, LexicalRanker()).rows.select("scope", "id")


@query(top_sql(EN256, "doc_id", LEX, 256))
def sort_docs_256(s, d):
    return ordered(topk.sort(items_of(first_english(s, d), "doc_id", payload=F.col("text")), LexicalRanker(ASK)))


@query(top_sql(EN256, "doc_id", LEX, 256))
def sort_proxy(s, d):
    return ordered(topk.sort(lexical_items(first_english(s, d)), PERFECT, RankParams(pivots=6, pivot_mode="proxy")))


@query(top_sql(EN256, "doc_id", LEX, 256))
def sort_pprime(s, d):
    return ordered(topk.sort(lexical_items(first_english(s, d)), PERFECT, RankParams(pivots=8, pivot_group=2)))


#: More rows than any table has: a full sort.
ALL_ROWS = 1_000_000_000_000
EN_SORTED = top_sql("documents", "doc_id", LEX, ALL_ROWS, "lang = 'en'")


@query(EN_SORTED)
def sort_docs_all(s, d):
    return ordered(topk.sort(items_of(every_english(s, d), "doc_id", payload=F.col("text")), LexicalRanker(ASK)))


@query(EN_SORTED)
def sort_proxy_all(s, d):
    return ordered(topk.sort(lexical_items(every_english(s, d)), PERFECT, RankParams(pivots=6, pivot_mode="proxy")))


@query(EN_SORTED)
def sort_pprime_all(s, d):
    return ordered(topk.sort(lexical_items(every_english(s, d)), PERFECT, RankParams(pivots=8, pivot_group=2)))


@query(top_sql("part", "p_partkey", "p_retailprice", ALL_ROWS))
def tournament_full_sort_all_parts(s, d):
    return ordered(topk.tournament_sort(items_of(load(s, d, "part"), "p_partkey", F.col("p_retailprice")), PERFECT))


@query(top_sql("orders", "o_orderkey", "o_totalprice", 1_000_000_000))
def sort_distributed_orders(s, d):
    return ordered(topk.sort(order_items(s, d), PERFECT, RankParams(pivots=6), tail=4_000))


@query(LINES10)
def select_then_sort_top10_lineitem(s, d):
    return ordered(topk.pivot_topk(line_items(s, d), 10, PERFECT, RankParams.default()))


@query(top_sql("documents", "doc_id", LEX, 20))
def refine_top10(s, d):
    return ordered(topk.pivot_topk(lexical_items(load(s, d, "documents")), 20, PERFECT, refine=10))


def kept_sql(size: int, s: int, turn: int = 0, source: str = "orders") -> str:
    return f"""(SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY bin ORDER BY o_totalprice DESC, o_orderkey) AS place FROM
 (SELECT o_orderkey, o_totalprice, (row_number() OVER (ORDER BY md5('42:{turn}:' || o_orderkey), o_orderkey) - 1) // {size} AS bin FROM {source})) WHERE place <= {s})"""


@query(f"SELECT o_orderkey AS id FROM {kept_sql(20, 1)}")
def filter_s1(s, d):
    return topk.bin_filter(order_items(s, d), PERFECT, RankParams(survivors=1)).rows.select("id")


@query(f"SELECT o_orderkey AS id FROM {kept_sql(20, 5)}")
def filter_s5(s, d):
    return topk.bin_filter(order_items(s, d), PERFECT, RankParams(survivors=5)).rows.select("id")


@query(f"SELECT o_orderkey AS id FROM {kept_sql(20, 2, 1, kept_sql(20, 2))}")
def filter_nested2(s, d):
    return topk.bin_filter(order_items(s, d), PERFECT, RankParams(survivors=2), rounds=2).rows.select("id")


@query("SELECT s, s * (n // 20) + least(s, n % 20) AS survivors FROM (SELECT count(*) AS n FROM orders), (SELECT unnest([1, 2, 5, 10, 15]) AS s)")
def filter_survivor_count(s, d):
    items = order_items(s, d)
    return experiments._all(topk.bin_filter(items, PERFECT, RankParams(survivors=x)).rows.agg(F.count("*").alias("survivors")).select(F.lit(x).alias("s"), "survivors") for x in (1, 2, 5, 10, 15))


_GRID_S, _GRID_K = (1, 2, 5, 10, 15), (1, 10, 50)
_PLACED = f"""placed AS (SELECT o_orderkey, place, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS r FROM {kept_sql(20, 20)}), cells AS (SELECT unnest([1, 2, 5, 10, 15]) AS s),
 ks AS (SELECT unnest([1, 10, 50]) AS k)"""


@query(f"WITH {_PLACED} SELECT s, k, round(sum(CASE WHEN place <= s THEN 1 ELSE 0 END) / CAST(count(*) AS DOUBLE), 9) AS recall FROM placed, cells, ks WHERE r <= k GROUP BY s, k")
def filter_recall_grid(s, d):
    return experiments.filter_recall(order_items(s, d), _GRID_S, _GRID_K).select("s", "k", F.round("recall", 9).alias("recall"))


@query(f"WITH {_PLACED} PIVOT (SELECT s, k, round(sum(CASE WHEN place <= s THEN 1 ELSE 0 END) / CAST(count(*) AS DOUBLE), 9) AS recall FROM placed, cells, ks WHERE r <= k GROUP BY s, k) ON k IN (1, 10, 50) USING first(recall) GROUP BY s")
def agg_pivot_recall_grid(s, d):
    return filter_recall_grid(s, d).groupBy("s").pivot("k", list(_GRID_K)).agg(F.first("recall"))


@query(top_sql(kept_sql(20, 2), "o_orderkey", "o_totalprice", 10))
def plan_filter_tournament(s, d):
    return ordered(planner.execute_plan(planner.Plan(True, 2, "tournament", 0, 0, 0, 0, 0), order_items(s, d), 10, PERFECT))


@query(top_sql(kept_sql(20, 2), "o_orderkey", "o_totalprice", 10))
def plan_filter_pivot(s, d):
    return ordered(planner.execute_plan(planner.Plan(True, 2, "pivot", 4, 6, 0, 0, 0), order_items(s, d), 10, PERFECT))


@query(ORDERS10)
def plan_tournament(s, d):
    return ordered(planner.execute_plan(planner.Plan(False, 0, "tournament", 0, 0, 0, 0, 0), order_items(s, d), 10, PERFECT))


@query(ORDERS10)
def plan_pivot(s, d):
    return ordered(planner.execute_plan(planner.Plan(False, 0, "pivot", 4, 6, 0, 0, 0), order_items(s, d), 10, PERFECT))


# ---- cost model --------------------------------------------------------------------------------------------------

_N, _K, _L = (256, 1000, 5183, 60000), (1, 10, 50, 100), (2, 5, 20, 64)
_G = "g AS (SELECT * FROM (SELECT unnest([256, 1000, 5183, 60000]) AS n), (SELECT unnest([1, 10, 50, 100]) AS k), (SELECT unnest([2, 5, 20, 64]) AS l))"
_COST_SELECT = "n * (p + 1) / (CAST(l - p AS DOUBLE) * (p - 1 + pow(CAST(k AS DOUBLE) / n, p + 1) + pow(1 - CAST(k AS DOUBLE) / n, p + 1)))"
_COST_SORT = "n * ln(n) / ((l - p) * ln(p + 1)) + 0.1 * n"


def grid(spark: SparkSession, columns: str, rows) -> DataFrame:
    """A small table of the cost model's parameters and values."""
    return spark.createDataFrame(list(rows), columns)


def sizes_sql(key: str, name: str = "n") -> str:
    return f"SELECT DISTINCT count(*) AS {name} FROM lineitem GROUP BY {key}"


#: The same parameters over the sizes that scopes have in the data: lines of a supplier.
_GT = f"g AS (SELECT * FROM ({sizes_sql('l_suppkey')}), (SELECT unnest([1, 10, 50, 100]) AS k), (SELECT unnest([2, 5, 20, 64]) AS l))"


def scope_grid(spark: SparkSession, sf_dir: str, columns: str, rows_of: Callable[[int], list[tuple]], key: str = "l_suppkey") -> DataFrame:
    """The cost model over every size that a key's groups of lines have, computed in tasks. rows_of(size): rows of ``columns``."""
    names = [c.split(" ")[0] for c in columns.split(", ")]

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            yield pd.DataFrame([row for n in part["n"] for row in rows_of(int(n))], columns=names)

    return load(spark, sf_dir, "lineitem").groupBy(key).agg(F.count("*").alias("n")).select("n").distinct().mapInPandas(run, columns)


@query(f"WITH {_GT} SELECT n, k, l, round((n - 1) / CAST(l - 1 AS DOUBLE) + k - 1, 6) AS unit, round((n + (k - 1) * ln(n) / ln(l)) / (l - 1), 6) AS remark, round((n - 1) / CAST(l - 1 AS DOUBLE) + (k - 1) * ln(n / CAST(l AS DOUBLE)), 6) AS summary FROM g WHERE n > 1")
def cost_tournament_grid(s, d):
    return scope_grid(s, d, "n bigint, k int, l int, unit double, remark double, summary double", lambda n: [(n, k, z, *(round(cost.cost_tournament(n, k, z, v), 6) for v in ("unit", "remark", "summary"))) for k in _K for z in _L if n > 1])


@query(f"WITH {_GT} SELECT n, k, l, p, round({_COST_SELECT}, 6) AS calls FROM g, (SELECT unnest(range(1, 64)) AS p) WHERE p < l AND n > l AND k < n AND (p > 1 OR k > 0)")
def cost_select_grid(s, d):
    return scope_grid(s, d, "n bigint, k int, l int, p bigint, calls double", lambda n: [(n, k, z, p, round(cost.cost_select(n, k, z, p), 6)) for k in _K for z in _L if k < n > z for p in range(1, z)])


@query(f"WITH {_GT} SELECT DISTINCT n, l, p, round({_COST_SORT}, 6) AS calls FROM g, (SELECT unnest(range(1, 64)) AS p) WHERE p < l AND n > l")
def cost_sort_grid(s, d):
    return scope_grid(s, d, "n bigint, l int, p bigint, calls double", lambda n: [(n, z, p, round(cost.cost_sort(n, z, p), 6)) for z in _L if n > z for p in range(1, z)])


@query(f"WITH {_GT} SELECT DISTINCT n, l, CAST(ceil(n / CAST(l AS DOUBLE)) AS BIGINT) AS calls FROM g")
def cost_filter_grid(s, d):
    return scope_grid(s, d, "n bigint, l int, calls bigint", lambda n: [(n, z, cost.cost_filter(n, z)) for z in _L])


@query(f"WITH {_GT} SELECT DISTINCT n, k, round(2.5 * n + k * ln(k), 6) AS pairwise, n AS pointwise FROM g")
def cost_pairwise_grid(s, d):
    return scope_grid(s, d, "n bigint, k int, pairwise double, pointwise bigint", lambda n: [(n, k, round(cost.cost_pairwise(n, k), 6), cost.cost_pointwise(n)) for k in _K])


_RECALL = """SELECT n, k, l, s, sum(CASE WHEN m < s THEN q ELSE 0 END) + s / lam * (1 - sum(CASE WHEN m <= s THEN q ELSE 0 END)) AS recall FROM
 (SELECT n, k, l, s, m, lam, exp(-lam + m * ln(lam) - lgamma(CAST(m + 1 AS DOUBLE))) AS q FROM (SELECT *, k * l / CAST(n AS DOUBLE) AS lam FROM g, ss), (SELECT unnest(range(0, 64)) AS m)) GROUP BY n, k, l, s, lam"""


@query(f"WITH {_GT}, ss AS (SELECT unnest([1, 2, 5, 10, 15]) AS s) SELECT n, k, l, s, round(recall, 6) AS recall FROM ({_RECALL}) WHERE s < l")
def filter_recall_poisson_grid(s, d):
    return scope_grid(s, d, "n bigint, k int, l int, s int, recall double", lambda n: [(n, k, z, x, round(cost.recall_filter(n, k, z, x), 6)) for k in _K for z in _L for x in _GRID_S if x < z])


@query(f"WITH {_GT} SELECT n, k, l, CAST(arg_min(p, c) AS BIGINT) AS p FROM (SELECT n, k, l, p, {_COST_SELECT} AS c FROM g, (SELECT unnest(range(1, 64)) AS p) WHERE p < l AND l > 2 AND n > l AND k < n) GROUP BY n, k, l")
def best_pivot_select(s, d):
    return scope_grid(s, d, "n bigint, k int, l int, p bigint", lambda n: [(n, k, z, cost.best_p_select(n, k, z)) for k in _K for z in _L if z > 2 and k < n > z])


@query(f"SELECT l, CAST(arg_min(p, 1 / ((l - p) * ln(p + 1))) AS BIGINT) AS p FROM ({sizes_sql('l_partkey', 'l')}), LATERAL (SELECT unnest(range(1, l)) AS p) WHERE l > 2 GROUP BY l")
def best_pivot_sort(s, d):
    """Lists as long as parts have lines."""
    return scope_grid(s, d, "l bigint, p bigint", lambda n: [(n, cost.best_p_sort(n))] if n > 2 else [], "l_partkey")


@query(f"WITH {_G}, ss AS (SELECT unnest(range(1, 64)) AS s) SELECT n, k, l, min(s) AS s FROM ({_RECALL}) WHERE s < l AND recall >= 0.95 GROUP BY n, k, l")
def min_survivors_grid(s, d):
    rows = ((n, k, z, cost.min_survivors(n, k, z, 0.95)) for n in _N for k in _K for z in _L)
    return grid(s, "n int, k int, l int, s bigint", (r for r in rows if r[3] is not None))


@query(f"WITH {_G} SELECT DISTINCT n, l, s, CAST(s * ceil(n / CAST(l AS DOUBLE)) AS BIGINT) AS bound, CAST(s * (n // l) + least(s, n % l) AS BIGINT) AS kept FROM g, (SELECT unnest([1, 2, 5]) AS s) WHERE s < l")
def n_after_filter_grid(s, d):
    return grid(s, "n int, l int, s int, bound bigint, kept bigint", ((n, z, x, cost.n_after_filter(n, z, x), topk.survivor_count(n, z, x)) for n in _N for z in _L for x in (1, 2, 5) if x < z))


@query(f"""WITH {_G}, ss AS (SELECT unnest(range(1, 64)) AS s), m AS (SELECT n, k, l, min(s) AS s FROM ({_RECALL}) WHERE s < l AND recall >= 0.95 GROUP BY n, k, l), r AS ({_RECALL}),
 f AS (SELECT n AS n0, k, l, s, s * CAST(ceil(n / CAST(l AS DOUBLE)) AS BIGINT) AS n, CAST(ceil(n / CAST(l AS DOUBLE)) AS DOUBLE) AS before, recall FROM m JOIN r USING (n, k, l, s) WHERE s * (n // l) + least(s, n % l) >= k
   UNION ALL SELECT n, k, l, 0, n, 0, 1 FROM g WHERE k < n),
 ps AS (SELECT unnest(range(1, 64)) AS p),
 sel AS (SELECT n0, k, l, s, min(CASE WHEN n <= l THEN 1 WHEN k >= n THEN 0 ELSE {_COST_SELECT} END) AS c FROM f, ps WHERE p < greatest(l, 2) AND (l > 2 OR p = 1) GROUP BY n0, k, l, s),
 srt AS (SELECT k, l, min(CASE WHEN k <= 1 THEN 0 WHEN k <= l THEN 1 ELSE k * ln(k) / ((l - p) * ln(p + 1)) + 0.1 * k END) AS c FROM (SELECT DISTINCT k, l FROM g), ps WHERE p < l GROUP BY k, l),
 plans AS (SELECT f.n0 AS n, k, l, recall, before + (f.n - 1) / CAST(l - 1 AS DOUBLE) + k - 1 AS calls FROM f WHERE f.n > 1
   UNION ALL SELECT f.n0, f.k, f.l, recall, before + sel.c + srt.c FROM f JOIN sel ON f.n0 = sel.n0 AND f.k = sel.k AND f.l = sel.l AND f.s = sel.s JOIN srt ON f.k = srt.k AND f.l = srt.l)
SELECT n, k, l, round(min(calls), 4) AS est_calls FROM plans GROUP BY n, k, l""")
def planner_choice(s, d):
    return grid(s, "n int, k int, l int, est_calls double", ((n, k, z, round(planner.choose_plan(n, k, z).est_calls, 4)) for n in _N for k in _K for z in _L))


@query()
def planner_explain(s, d):
    return planner.explain_semantic(s, 5183, 10)


# ---- baselines, gold, measures -----------------------------------------------------------------------------------


@query(top_sql("documents", "doc_id", LEX, 10))
def pairwise_prior_top10(s, d):
    return ordered(baselines.pairwise_prior(lexical_items(load(s, d, "documents")), 10, PERFECT))


@query(top_sql("documents", "doc_id", LEX, 10))
def pairwise_list_top10(s, d):
    return ordered(baselines.pairwise_list(lexical_items(load(s, d, "documents")), 10, PERFECT))


class _Exact(PointScorer):
    """A calibrated scorer: the response is the score itself."""

    def respond(self, request):
        return f" {self.base.score(request, 0):.1f} "


@query(top_sql("documents", "doc_id", LEX, 10))
def pointwise_top10(s, d):
    return ordered(baselines.pointwise_topk(lexical_items(load(s, d, "documents")), 10, _Exact(PERFECT, 100)))


@query("SELECT response, CAST(coalesce(TRY_CAST(trim(response) AS DOUBLE), 50) AS DOUBLE) AS score FROM (VALUES ('87'), (' 12.5 '), ('n/a'), ('')) t(response)")
def pointwise_imputed(s, d):
    return s.createDataFrame([("87",), (" 12.5 ",), ("n/a",), ("",)], "response string").select("response", baselines.parsed_score(F.col("response"), 100).alias("score"))


_QRELS = "SELECT item_id AS scope, doc_id AS id FROM benchmark b JOIN documents d ON contains(d.text, b.text)"


def _bench(s, d, where: str = "true") -> DataFrame:
    return load(s, d, "benchmark").filter(where).select(F.col("item_id").alias("scope"), F.col("text").alias("query"))


@query(f"SELECT scope, id, 1 AS rel FROM ({_QRELS})")
def gold_sparse_qrels(s, d):
    return baselines.sparse_gold(_bench(s, d), experiments.corpus(s, d))


_OVERLAP_ALL = "SELECT item_id AS scope, doc_id AS id, " + scores_sql("b.text", "d.text") + " AS overlap FROM benchmark b, documents d"


@query(f"SELECT scope, id, overlap, r FROM (SELECT *, row_number() OVER (PARTITION BY scope ORDER BY overlap DESC, id) AS r FROM ({_OVERLAP_ALL}) WHERE overlap > 0) WHERE r <= 50")
def gold_overlap_top50_all(s, d):
    return _overlap_top50(s, d)


def _overlap_top50(s, d, where: str = "true") -> DataFrame:
    from pyspark.sql import Window as W

    x = baselines.token_overlap(_bench(s, d, where), experiments.corpus(s, d))
    return x.withColumn("r", F.row_number().over(W.partitionBy("scope").orderBy(F.desc("overlap"), "id")).cast("long")).filter("r <= 50").select("scope", "id", "overlap", "r")


@query()
def ensemble_rrf(s, d):
    return baselines.ensemble_retrieve(_bench(s, d), experiments.corpus(s, d))


@query()
def elo_top10(s, d):
    return baselines.judge_gold(_bench(s, d), experiments.corpus(s, d))


def _query_top10(s, d, where: str = "true") -> DataFrame:
    q = _bench(s, d, where)
    docs = experiments.corpus(s, d)
    hits = baselines.token_overlap(q, docs)
    items = q.select("scope").crossJoin(docs.select("id")).join(hits, ["scope", "id"], "left").select("scope", "id", F.lit(None).cast("string").alias("payload"), F.coalesce("overlap", F.lit(0)).cast("double").alias("score"), F.lit(None).cast("double").alias("proxy"))
    return topk.pivot_topk(items, 10, PERFECT).rows


_TOP10_ALL = f"SELECT scope, id, r AS rank FROM (SELECT *, row_number() OVER (PARTITION BY scope ORDER BY overlap DESC, id) AS r FROM ({_OVERLAP_ALL})) WHERE r <= 10"


@query(f"WITH t AS ({_TOP10_ALL}), q AS ({_QRELS}) SELECT q.scope, round(count(t.id) / CAST(count(*) AS DOUBLE), 9) AS recall FROM q LEFT JOIN t ON q.scope = t.scope AND q.id = t.id GROUP BY q.scope")
def recall_at_10_all(s, d):
    gold = baselines.sparse_gold(_bench(s, d), experiments.corpus(s, d))
    return metrics.recall_at_k(_query_top10(s, d), gold, 10).select("scope", F.round("recall", 9).alias("recall"))


@query(f"""WITH t AS ({_TOP10_ALL}), q AS (SELECT *, row_number() OVER (PARTITION BY scope ORDER BY id) AS i FROM ({_QRELS}))
SELECT q.scope, round(coalesce(sum(1 / log2(t.rank + 1)), 0) / sum(CASE WHEN i <= 10 THEN 1 / log2(i + 1) ELSE 0 END), 9) AS ndcg FROM q LEFT JOIN t ON q.scope = t.scope AND q.id = t.id GROUP BY q.scope""")
def ndcg_at_10_all(s, d):
    gold = baselines.sparse_gold(_bench(s, d), experiments.corpus(s, d))
    return metrics.ndcg_at_k(_query_top10(s, d), gold, 10).select("scope", F.round("ndcg", 9).alias("ndcg"))


_MID = "rank() OVER (ORDER BY {0}) + (count(*) OVER (PARTITION BY {0}) - 1) / 2.0"


@query(f"SELECT CAST(0 AS BIGINT) AS scope, round(corr(x, y), 6) AS spearman FROM (SELECT {_MID.format('n_chars')} AS x, {_MID.format('l')} AS y FROM (SELECT n_chars, {LEX} AS l FROM {EN256}))")
def spearman_sort(s, d):
    x = lexical_items(first_english(s, d))
    return metrics.spearman(x.select("scope", "id", F.col("proxy").alias("value")), x.select("scope", "id", F.col("score").alias("value"))).select("scope", F.round("spearman", 6).alias("spearman"))


@query(f"SELECT CAST(0 AS BIGINT) AS scope, round(corr(x, y), 6) AS spearman FROM (SELECT {_MID.format('n_chars')} AS x, {_MID.format('l')} AS y FROM (SELECT n_chars, {LEX} AS l FROM documents WHERE lang = 'en'))")
def spearman_sort_all(s, d):
    x = lexical_items(every_english(s, d))
    return metrics.spearman(x.select("scope", "id", F.col("proxy").alias("value")), x.select("scope", "id", F.col("score").alias("value"))).select("scope", F.round("spearman", 6).alias("spearman"))


@query("SELECT CAST(ceil(count(*) / 20.0) AS BIGINT) AS calls, count(*) AS items FROM orders")
def calls_filter(s, d):
    return metrics.count_calls(topk.bin_filter(order_items(s, d), PERFECT, RankParams()).calls).select("calls", "items")


@query("SELECT count(*) AS calls FROM documents")
def calls_pointwise(s, d):
    return metrics.count_calls(baselines.pointwise_topk(lexical_items(load(s, d, "documents")), 10, PointScorer(PERFECT, 100)).calls).select("calls")


@query("SELECT CAST(ceil(count(*) / 20.0) AS BIGINT) AS calls FROM orders")
def calls_first_tournament_round(s, d):
    calls = topk.tournament(order_items(s, d), 1, PERFECT, tail=1_000).calls
    return metrics.count_calls(calls.filter("call_id like '0:tournament:0:0:bin:0.%'")).select("calls")


@query()
def calls_information(s, d):
    return metrics.implied_pairs(topk.bin_filter(order_items(s, d), PERFECT, RankParams()).calls)


@query()
def calls_critical_path(s, d):
    return metrics.critical_path(topk.tournament(order_items(s, d), 10, PERFECT).calls, 4)


_POINTS = "(VALUES (2, 30.5), (5, 17.25), (10, 13.5), (20, 12.75), (40, 16.0), (64, 21.0), (96, 29.5)) t(x, y)"


def _points(s) -> DataFrame:
    return s.createDataFrame([(2, 30.5), (5, 17.25), (10, 13.5), (20, 12.75), (40, 16.0), (64, 21.0), (96, 29.5)], "x int, y double")


@query(f"SELECT round(regr_slope(y, x), 6) AS a, round(regr_intercept(y, x), 6) AS b FROM {_POINTS}")
def fit_linear(s, d):
    a, b = metrics.fit(_points(s), "x", "y")
    return s.createDataFrame([(round(a, 6), round(b, 6))], "a double, b double")


@query(f"""WITH p AS (SELECT CAST(x AS DOUBLE) AS u, 1 / CAST(x AS DOUBLE) AS v, CAST(y AS DOUBLE) AS y FROM {_POINTS}), m AS (SELECT avg(u) AS mu, avg(v) AS mv, avg(y) AS my FROM p),
 z AS (SELECT sum((u-mu)*(u-mu)) AS uu, sum((v-mv)*(v-mv)) AS vv, sum((u-mu)*(v-mv)) AS uv, sum((u-mu)*(y-my)) AS uy, sum((v-mv)*(y-my)) AS vy FROM p, m)
SELECT round((uy*vv - vy*uv) / (uu*vv - uv*uv), 6) AS a, round((vy*uu - uy*uv) / (uu*vv - uv*uv), 6) AS c, round(sqrt(((vy*uu - uy*uv)) / (uy*vv - vy*uv)), 4) AS best FROM z""")
def fit_reciprocal(s, d):
    a, _, c = metrics.fit(_points(s), "x", "y", "reciprocal")
    return s.createDataFrame([(round(a, 6), round(c, 6), round(metrics.best_list_size(a, c), 4))], "a double, c double, best double")


_METHODS = [("a", 10.0, 0.5), ("b", 20.0, 0.7), ("c", 15.0, 0.5), ("d", 20.0, 0.6), ("e", 40.0, 0.9)]
_METHODS_SQL = "(VALUES " + ", ".join(f"('{m}', CAST({c} AS DOUBLE), CAST({a} AS DOUBLE))" for m, c, a in _METHODS) + ") t(algo, calls, accuracy)"


@query(f"SELECT * FROM {_METHODS_SQL} WHERE NOT EXISTS (SELECT 1 FROM {_METHODS_SQL.replace(' t(', ' u(')} WHERE u.calls <= t.calls AND u.accuracy >= t.accuracy AND (u.calls < t.calls OR u.accuracy > t.accuracy))")
def pareto_front(s, d):
    return metrics.pareto(s.createDataFrame(_METHODS, "algo string, calls double, accuracy double"))


@query(f"SELECT algo, calls AS value, round(10 / calls, 6) AS speedup, round(100 * (calls / 10 - 1), 6) AS overhead_pct FROM {_METHODS_SQL}")
def speedup_table(s, d):
    return metrics.speedup(s.createDataFrame(_METHODS, "algo string, calls double, accuracy double"), "a").select("algo", "value", F.round("speedup", 6).alias("speedup"), F.round("overhead_pct", 6).alias("overhead_pct"))


# ---- kernel pieces -----------------------------------------------------------------------------------------------


@query("""SELECT id, bucket FROM (SELECT id, early, CAST(coalesce(sum(CASE WHEN early <= 2 THEN 1 ELSE 0 END) OVER (PARTITION BY scope ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS INTEGER) AS bucket FROM
 (SELECT o_custkey AS scope, o_orderkey AS id, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS place, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS early FROM orders)) WHERE early > 2""")
def contradiction_bucket(s, d):
    """A customer's orders by price; pivots are the first two, settled by key, which the prices contradict for half of the customers."""
    by_price = F.array_sort(F.collect_list(F.struct((-F.col("o_totalprice")).alias("k"), F.col("o_orderkey").alias("id"))))
    x = load(s, d, "orders").groupBy("o_custkey").agg(F.transform(by_price, lambda o: o["id"]).alias("ranked"), F.slice(F.sort_array(F.collect_list("o_orderkey")), 1, 2).alias("pivots"))
    return x.select(F.inline(prompts.bucket_column(F.col("ranked"), F.col("pivots"))))


@query("SELECT positions, n, list_concat(known, list_filter(CAST(range(1, n + 1) AS INT[]), lambda x: NOT list_contains(known, x))) AS fixed FROM (SELECT *, CASE n WHEN 4 THEN [1, 3] WHEN 3 THEN [2, 1, 3] ELSE CAST([] AS INT[]) END AS known FROM (VALUES ([1, 1, 9, 3], 4), ([2, 1, 3], 3), (CAST([] AS INT[]), 2)) t(positions, n))")
def repair_rankings(s, d):
    x = s.createDataFrame([([1, 1, 9, 3], 4), ([2, 1, 3], 3), ([], 2)], "positions array<int>, n int")
    return x.select("positions", "n", prompts.repair_column(F.col("positions"), F.col("n")).alias("fixed"))


@query("SELECT doc_id AS id, 'Order the passages by relevance to: x' || chr(10) || '[1] ' || substr(text, 1, 50) || chr(10) || '[2] ' || coalesce(lang, '') || chr(10) || 'Answer with all numbers, most relevant first.' AS prompt FROM documents")
def listwise_prompt(s, d):
    x = load(s, d, "documents")
    return x.select(F.col("doc_id").alias("id"), prompts.prompt_column(F.lit("x"), F.array(prompts.clip_payload(F.col("text"), 50), F.coalesce("lang", F.lit("")))).alias("prompt"))


@query("SELECT doc_id AS id, 'Order the passages by relevance to: x' || chr(10) || '[1] ' || text || chr(10) || '[2] ' || coalesce(lang, '') || chr(10) || 'Answer with all numbers, most relevant first.' AS prompt FROM documents")
def listwise_prompt_whole(s, d):
    x = load(s, d, "documents")
    return x.select(F.col("doc_id").alias("id"), prompts.prompt_column(F.lit("x"), F.array(F.col("text"), F.coalesce("lang", F.lit("")))).alias("prompt"))


@query("SELECT bin, count(*) AS n, min(o_orderkey) AS least FROM (SELECT o_orderkey, (row_number() OVER (ORDER BY md5('42:0:' || o_orderkey), o_orderkey) - 1) // 20 AS bin FROM orders) GROUP BY bin")
def bins_exact(s, d):
    return binning.assign_bins(order_items(s, d), 20, 42, 0).groupBy("bin").agg(F.count("*").alias("n"), F.min("id").alias("least"))


@query("SELECT n, count(*) AS bins FROM (SELECT pos % bins AS bin, count(*) AS n FROM (SELECT row_number() OVER () - 1 AS pos FROM orders), (SELECT CAST(ceil(count(*) / 64.0) AS BIGINT) AS bins FROM orders) GROUP BY bin) GROUP BY n")
def bins_balanced(s, d):
    return binning.assign_bins(order_items(s, d), 64, 42, 0, mode="balanced").groupBy("bin").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("bins"))


@query(f"SELECT bin, o_orderkey AS worse, lag(o_orderkey) OVER (PARTITION BY bin ORDER BY place) AS better FROM {kept_sql(20, 20)} QUALIFY better IS NOT NULL")
def win_lag_edges(s, d):
    done = rank_lists(lists_of(binning.assign_bins(order_items(s, d), 20, 42, 0), ["scope"], "bin"), PERFECT)
    return done.select("bin", F.posexplode("ranked.id").alias("p", "worse"), F.col("ranked.id").alias("all")).filter("p > 0").select("bin", "worse", F.expr("get(all, p - 1)").alias("better"))


# ---- simulation --------------------------------------------------------------------------------------------------


@query()
def simulate_select(s, d):
    return simulate.compare_theory(s, "select", [{"n": 1000, "k": k, "size": 20, "p": p} for k in (1, 10, 100, 500) for p in (1, 2, 4, 6, 10)], simulate.TRIALS)


@query()
def simulate_sort(s, d):
    return simulate.compare_theory(s, "sort", [{"n": 1000, "size": 20, "p": p} for p in (1, 2, 4, 6, 8, 12, 16)], simulate.TRIALS)


@query()
def simulate_filter(s, d):
    return simulate.simulate_grid(s, "filter", [{"n": 5183, "k": k, "size": 20, "s": x} for k in (10, 50) for x in (1, 2)], simulate.TRIALS)


@query()
def simulate_tournament(s, d):
    return simulate.simulate_grid(s, "tournament", [{"n": 1000, "k": k, "size": 20} for k in (1, 10)], simulate.TRIALS)


@query()
def simulate_pivot_groups(s, d):
    return simulate.simulate_grid(s, "select", [{"n": 5183, "k": 10, "size": 20, "p": p, "group": g, "early_stop": e} for p, g, e in ((4, 4, False), (4, 2, True), (8, 2, True), (16, 2, True), (16, 2, False), (16, 16, False))], simulate.TRIALS)


# ---- experiments -------------------------------------------------------------------------------------------------


@query()
def w_four_plans(s, d):
    return experiments.four_plans(experiments.claim_items(s, d), experiments.fine())


@query()
def w_methods(s, d):
    return experiments.method_table(experiments.claim_items(s, d))


@query()
def w_pareto(s, d):
    return experiments.pareto_methods(s, d)


@query()
def w_judge_labels(s, d):
    return experiments.judge_workload(s, d)


@query()
def w_review_sort(s, d):
    return experiments.review_sort(s, d)


@query()
def w_review_sort_conversations(s, d):
    return experiments.review_sort(s, d, "conversations")


@query()
def w_list_size(s, d):
    return experiments.sweep_list_size(experiments.claim_items(s, d))


@query()
def w_k(s, d):
    return experiments.sweep_k(experiments.claim_items(s, d))


@query()
def w_pivots(s, d):
    return experiments.sweep_p(experiments.claim_items(s, d))


@query()
def w_sort_sweeps(s, d):
    return experiments.sweep_sort(s, d)


@query()
def w_proxy_pivots(s, d):
    return experiments.proxy_pivots(s, d)


@query()
def w_pivot_groups(s, d):
    return experiments.pivot_groups(experiments.claim_items(s, d))


@query()
def w_refinement(s, d):
    return experiments.refinement(experiments.claim_items(s, d))


@query()
def w_tuning_gain(s, d):
    return experiments.tuning_gain(s)


@query()
def w_reduced_corpus(s, d):
    return experiments.reduced_corpus(s, d)


@query(top_sql("documents", "doc_id", LEX, 20, "lang = 'en'"))
def w_papers_for_project(s, d):
    x = load(s, d, "documents").filter("lang = 'en'")
    return api.sem_order_by(x, "text", ASK, limit=20).select("rank", F.col("doc_id").alias("id"))


@query(top_sql("customer", "c_custkey", "c_acctbal", 5).replace("OVER (ORDER", "OVER (PARTITION BY c_mktsegment ORDER").replace("AS id FROM customer", "AS id, c_mktsegment AS segment FROM customer").replace("SELECT rank, id", "SELECT segment, rank, id"))
def w_customers_per_segment(s, d):
    c = load(s, d, "customer")
    names = c.select("c_mktsegment").distinct().withColumn("scope", F.xxhash64("c_mktsegment"))
    done = topk.pivot_topk(items_of(c, "c_custkey", F.col("c_acctbal"), scope=F.xxhash64("c_mktsegment")), 5, PERFECT)
    return done.rows.join(names, "scope").select(F.col("c_mktsegment").alias("segment"), "rank", "id")


# ---- SQL surface, UDFs, streams ----------------------------------------------------------------------------------


@query(top_sql("documents", "doc_id", LEX, 10, "lang = 'en' AND n_chars < 5000"))
def sem_sql_order_limit(s, d):
    register_views(s, d, ["documents"])
    out = sqlfront.semantic_sql(s, f"SELECT doc_id, text FROM documents WHERE lang = 'en' AND n_chars < 5000 ORDER BY SEMANTIC('{ASK}', text) LIMIT 10")
    return out.select("rank", F.col("doc_id").alias("id"))


@query(top_sql("documents", "doc_id", LEX, 10, "lang = 'en' AND n_chars < 5000"))
def filter_then_semantic(s, d):
    x = load(s, d, "documents").filter("lang = 'en' and n_chars < 5000")
    return api.sem_order_by(x, "text", ASK, limit=10).select("rank", F.col("doc_id").alias("id"))


_LANG10 = f"SELECT lang AS scope, r AS rank, doc_id AS id FROM (SELECT *, row_number() OVER (PARTITION BY lang ORDER BY {LEX} DESC, doc_id) AS r FROM documents) WHERE r <= 10"


@query(_LANG10)
def sem_udtf_topk(s, d):
    udfs.register(s)
    load(s, d, "documents").select(F.col("lang").alias("scope"), F.col("doc_id").alias("id"), "text").createOrReplaceTempView("ranked_docs")
    return s.sql(f"SELECT * FROM semantic_topk(TABLE(ranked_docs) PARTITION BY (scope), '{ASK}', 10)")


@query(_LANG10)
def udf_grouped_topk(s, d):
    return udfs.grouped_topk(load(s, d, "documents"), "lang", "doc_id", "text", ASK, 10)


@query(f"SELECT doc_id AS id, {LEX} AS score FROM documents")
def udf_pandas_score(s, d):
    return load(s, d, "documents").select(F.col("doc_id").alias("id"), udfs.semantic_score()("text", F.lit(ASK)).alias("score"))


@query("SELECT lang, round(sum(quality / log2(r + 1)) / sum(quality / log2(i + 1)), 6) AS ndcg FROM (SELECT lang, quality, row_number() OVER (PARTITION BY lang ORDER BY doc_id) AS r, row_number() OVER (PARTITION BY lang ORDER BY quality DESC, doc_id) AS i FROM documents JOIN labels USING (doc_id)) GROUP BY lang")
def udaf_pandas_ndcg(s, d):
    from pyspark.sql import Window as W

    x = load(s, d, "documents").join(load(s, d, "labels"), "doc_id").select("lang", "quality", F.row_number().over(W.partitionBy("lang").orderBy("doc_id")).alias("r"))
    return x.groupBy("lang").agg(udfs.ndcg_udaf()("r", "quality").alias("ndcg")).select("lang", F.round("ndcg", 6).alias("ndcg"))


_TYPES = "CAST(length(event_type) * 100 + ascii(event_type) AS BIGINT)"


def _event_items(s, d) -> DataFrame:
    return items_of(streams.file_stream(s, d, "events"), "event_id", F.col("value"), scope=F.expr("length(event_type) * 100 + ascii(event_type)"))


@query(f"SELECT scope, id FROM (SELECT {_TYPES} AS scope, event_id AS id, row_number() OVER (PARTITION BY {_TYPES} ORDER BY value DESC, event_id) AS r FROM events) WHERE r <= 10")
def stream_running_topk(s, d):
    path = work_path(s, "running")
    run = streams.running_topk(_event_items(s, d), 10, PERFECT, path)
    run.awaitTermination()
    return streams.latest_topk(s, path, run).select("scope", "id")


@query("""WITH x AS (SELECT *, time_bucket(INTERVAL 1 DAY, ts) AS start FROM events), m AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events)
SELECT event_type, start, r AS rank, event_id AS id, value FROM (SELECT *, row_number() OVER (PARTITION BY event_type, start ORDER BY value DESC, event_id) AS r FROM x) , m WHERE r <= 3 AND start + INTERVAL 1 DAY <= mark""")
def stream_tumbling_topk(s, d):
    stream = streams.file_stream(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    out = streams.to_table(streams.windowed_topk(stream, 3, "event_type", "ts", "event_id", "value", "1 day"), work_path(s, "windows"))
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("""WITH o AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new, event_id FROM events),
 g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM o), m AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events)
SELECT user_id, start, n FROM (SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS n FROM g GROUP BY user_id, g), m WHERE stop <= mark""")
def stream_session_counts(s, d):
    stream = streams.file_stream(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    marked, w = streams.windowed(stream, "ts", "", gap="30 minutes")
    counts = marked.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")
    return streams.to_table(counts, work_path(s, "sessions")).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(f"SELECT scope, CAST(4 * (n // 20) AS BIGINT) AS survivors FROM (SELECT {_TYPES} AS scope, count(*) AS n FROM events GROUP BY 1)")
def stream_bin_filter(s, d):
    s.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    out = streams.to_table(streams.stream_filter(_event_items(s, d), 20, 4, PERFECT), work_path(s, "bins"))
    return out.filter("n_items = 20").groupBy("scope").agg(F.count("*").alias("survivors"))


@query("SELECT count(DISTINCT text) AS n FROM documents")
def stream_dedup_documents(s, d):
    """Null texts are none of the counted ones, as in SQL."""
    stream = streams.file_stream(s, d, "documents", 8).filter("text is not null").select(F.sha2(F.col("text").cast("binary"), 256).alias("h"), F.expr("timestamp '2024-01-01 00:00:00'").alias("seen"))
    out = streams.to_table(stream.withWatermark("seen", "1 hour").dropDuplicatesWithinWatermark(["h"]), work_path(s, "dedup"))
    return out.agg(F.count("*").alias("n"))


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY event_type")
def stream_complete_counts(s, d):
    path = work_path(s, "complete")
    counts = streams.file_stream(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    streams.each_batch(counts, path, lambda batch, number: batch.write.mode("overwrite").parquet(f"{path}/out"), "complete")
    return s.read.schema("event_type string, n bigint, total double").parquet(f"{path}/out")


@query("SELECT d.doc_id, quality FROM documents d JOIN labels l ON d.doc_id = l.doc_id WHERE toxic = 1")
def stream_static_join(s, d):
    joined = streams.file_stream(s, d, "documents", 8).select("doc_id").join(load(s, d, "labels").filter("toxic = 1"), "doc_id").select("doc_id", "quality")
    return streams.to_table(joined, work_path(s, "static"))


@query("SELECT a.event_id AS view_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR")
def stream_stream_join(s, d):
    one = lambda kind, name: streams.file_stream(s, d, "events").filter(F.col("event_type") == kind).select(F.col("event_id").alias(name), F.col("user_id").alias(f"{name}_user"), F.col("ts").cast("timestamp").alias(f"{name}_ts")).withWatermark(f"{name}_ts", "2 hours")
    a, b = one("view", "view_id"), one("purchase", "buy_id")
    joined = a.join(b, F.expr("view_id_user = buy_id_user and buy_id_ts between view_id_ts and view_id_ts + interval 1 hour")).select("view_id", "buy_id")
    return streams.to_table(joined, work_path(s, "pairs"))


# ---- further workloads and measures ------------------------------------------------------------------------------


@query("SELECT row_number() OVER (ORDER BY md5('42:floor:' || doc_id), doc_id) AS rank, doc_id AS id FROM documents QUALIFY rank <= 10")
def random_order_top10(s, d):
    """The floor of every measure: documents in the order of a hash."""
    x = items_of(load(s, d, "documents"), "doc_id")
    return binning.positions(x, 42, "floor", ["scope"]).filter("pos < 10").select((F.col("pos") + 1).alias("rank"), "id")


@query(f"WITH {_GT} SELECT DISTINCT n, round(1 - ((n // 20) * 190 + (n % 20) * (n % 20 - 1) / 2.0) / (CAST(n AS DOUBLE) * (n - 1) / 2.0) / 2, 9) AS recall FROM g WHERE n > 1")
def filter_recall_exact_grid(s, d):
    """Hypergeometric recall for K = 2 and one survivor: a half is lost when both share a bin."""
    return scope_grid(s, d, "n bigint, recall double", lambda n: [(n, round(cost.recall_filter(n, 2, 20, 1, "exact"), 9))] if n > 1 else [])


@query()
def exact_select_cost(s, d):
    """Expected calls of select from the exact chain, beside the self-similar form, over as many documents as parts have lines."""
    return scope_grid(s, d, "n bigint, k int, p int, exact double, formula double", lambda n: [(n, k, p, simulate.exact_select_cost(n, k, 20, p), cost.cost_select(n, k, 20, p)) for k in (5, 10) for p in (1, 2, 4, 6)], "l_partkey")


@query()
def sort_coefficient(s, d):
    """The linear term of the sort cost, fitted to simulations."""
    return grid(s, "p int, c double", ((p, simulate.fit_sort_coefficient(s, 20, p)) for p in (4, 6)))


@query()
def w_filter_recall_queries(s, d):
    """Filter recall on the claim workload for S up to 15 and K up to 50, averaged over queries."""
    got = experiments.filter_recall(experiments.claim_items(s, d), (1, 2, 3, 5, 8, 10, 15), (1, 5, 10, 20, 50))
    return got.groupBy("s", "k").agg(F.avg("recall").alias("recall"))


@query(top_sql("(SELECT page_id, strlen(html) AS n FROM pages)", "page_id", "n", 1_000_000_000))
def w_pages_full_sort(s, d):
    """A full sort of pages by how much they hold."""
    x = items_of(load(s, d, "pages"), "page_id", F.octet_length("html").cast("double"))
    return ordered(planner.execute_plan(planner.choose_plan(250, 250, mode="sort"), x, 1_000_000_000, PERFECT))


@query(top_sql("part", "p_partkey", "p_retailprice", 20))
def w_parts_by_price(s, d):
    x = load(s, d, "part")
    return api.semantic_topk(x, "p_partkey", 20, PERFECT, score=F.col("p_retailprice")).select("rank", F.col("p_partkey").alias("id"))


@query()
def calls_quality_rates(s, d):
    """How often responses needed repair or contradicted the settled order of pivots."""
    from ..operators.rankers import BrokenRanker, ContradictingRanker

    items = lexical_items(every_english(s, d))
    runs = (("broken", BrokenRanker(PERFECT)), ("contradicting", ContradictingRanker(PERFECT, 0.3)), ("perfect", PERFECT))
    return experiments._all(metrics.quality_rates(topk.sort(items, r, RankParams(pivots=6)).calls).withColumn("ranker", F.lit(n)) for n, r in runs)


@query()
def w_sparse_labels(s, d):
    return experiments.sparse_labels(s, d)


@query()
def w_judge_methods(s, d):
    return experiments.judge_labels(s, d)


@query("SELECT true AS early_stop_is_cheaper, true AS like_measured")
def planner_operating_point(s, d):
    """The default operating point by simulation against the same pivots without early stop, and against 312 calls measured for a perfect ranker."""
    own = planner.operating_point_calls(s, 5183, 10)
    plain = planner.operating_point_calls(s, 5183, 10, RankParams(pivots=16, pivot_group=2))
    return s.createDataFrame([(own < plain, abs(own - 313) < 13)], "early_stop_is_cheaper boolean, like_measured boolean")
