"""Ordering a DataFrame by a natural-language criterion.

The criterion stays an argument of the operator, so filters and projections of the input run below every ranker call,
and only id and text travel through ranking; winners take their other columns back by a join at the end.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.rankers import LexicalRanker, Ranker
from ..operators.topk import TAIL, turned
from ..plans.planner import choose_plan, execute_plan
from ..schema import RankParams
from ..sources.tables import assert_unique_id, items_of, payload_of


def prepare_items(df: DataFrame, id_col: str, text_cols: str | list[str] | None = None, score: Column | None = None, proxy: Column | None = None, scope: Column | None = None) -> DataFrame:
    names = [text_cols] if isinstance(text_cols, str) else text_cols
    return items_of(df, id_col, score, payload_of(df.schema, names) if names else None, proxy, scope)


def attach(df: DataFrame, rows: DataFrame, id_col: str) -> DataFrame:
    """The ranked rows of ``df`` with column ``rank``. Spark broadcasts the winners if they are few."""
    return df.join(rows.select(F.col("id").alias("_id"), "rank"), F.col(id_col) == F.col("_id")).drop("_id")


def semantic_topk(df: DataFrame, id_col: str, k: int | None, ranker: Ranker, text_cols: str | list[str] | None = None, score: Column | None = None, list_size: int = 20, recall_target: float = 1.0, n: int | None = None, seed: int = 42, refine: int = 0, override: RankParams | None = None, check_ids: bool = True, tail: int = TAIL, ascending: bool = False) -> DataFrame:
    """``df``'s first k rows (all for k None) by the ranker, with ``rank`` from 1; ascending: the last, the least relevant first. n: a row count from statistics saves the count."""
    items = prepare_items(df, id_col, text_cols, score)
    if check_ids:
        assert_unique_id(items)
    if ascending:
        items, ranker = turned(items, ranker)
    n = df.count() if n is None else n
    if n == 0 or k == 0:
        return df.limit(0).withColumn("rank", F.lit(None).cast("long"))
    plan = choose_plan(n, n if k is None else min(k, n), list_size, recall_target, "sort" if k is None else "topk")
    done = execute_plan(plan, items, n if k is None else min(k, n), ranker, list_size, seed, refine=refine, override=override, tail=tail)
    return attach(df, done.rows, id_col)


def sem_order_by(df: DataFrame, text_col: str, query: str, id_col: str = "doc_id", limit: int | None = None, ranker: Ranker | None = None, recall_target: float = 1.0, **options) -> DataFrame:
    """ORDER BY the relevance of ``text_col`` to ``query`` [LIMIT limit]."""
    return semantic_topk(df, id_col, limit, ranker or LexicalRanker(query), text_col, recall_target=recall_target, **options)
