"""Pandas UDFs and the table function of the SQL surface."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.udtf import AnalyzeResult
from pyspark.sql import types as T

from ..operators.engine import Doc, Judge
from ..operators.rankers import LexicalRanker, tokens
from ..schema import RankParams


def register(spark: SparkSession) -> None:
    """semantic_score(text, query), ndcg_of(rels) and the table function semantic_topk."""
    spark.udf.register("semantic_score", semantic_score())
    spark.udtf.register("semantic_topk", F.udtf(SemanticTopK))


def semantic_score():
    """Distinct query tokens that a text holds."""

    def score(text: pd.Series, query: pd.Series) -> pd.Series:
        known: dict[str, set[str]] = {}
        return pd.Series([len(known.setdefault(q or "", tokens(q)) & tokens(t)) for t, q in zip(text, query, strict=True)], dtype="int64")

    return F.pandas_udf(score, "bigint")


def ndcg_udaf():
    """NDCG of a group from (rank, rel): a grouped aggregate."""

    def ndcg(rank: pd.Series, rel: pd.Series) -> float:
        got = sum(r / math.log2(p + 1) for p, r in zip(rank, rel, strict=True))
        ideal = sum(r / math.log2(p + 1) for p, r in enumerate(sorted(rel, reverse=True), 1))
        return got / ideal if ideal else 0.0

    return F.pandas_udf(ndcg, "double")


def grouped_topk(df: DataFrame, scope: str, id_col: str, text: str, query: str, k: int) -> DataFrame:
    """The k best of each group in one task per group, by lists of 20: for groups known to be small."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        from ..operators.engine import pivot_select, pivot_sort

        docs = {int(i): Doc(int(i), t) for i, t in zip(part["id"], part["text"], strict=True)}
        judge = Judge(docs, LexicalRanker(query), RankParams())
        got = pivot_sort(judge, pivot_select(judge, sorted(docs), k))
        return pd.DataFrame({"scope": part["scope"].iloc[0], "rank": range(1, len(got) + 1), "id": got})

    kind = df.schema[scope].dataType.simpleString()
    return df.select(F.col(scope).alias("scope"), F.col(id_col).alias("id"), F.col(text).alias("text")).groupBy("scope").applyInPandas(run, f"scope {kind}, rank bigint, id bigint")


class SemanticTopK:
    """``semantic_topk(TABLE(t) PARTITION BY (scope), query, k)`` over columns scope, id, text.

    Rows arrive one by one; a list of L is ranked whenever k kept ones and new ones fill it, so memory stays at L rows (2 k for k >= L).
    """

    def __init__(self):
        self.docs: dict[int, Doc] = {}
        self.scope = None
        self.query, self.k = "", 0

    @staticmethod
    def analyze(table, query, k) -> AnalyzeResult:
        fields = {f.name: f.dataType for f in table.dataType.fields}
        return AnalyzeResult(T.StructType().add("scope", fields["scope"]).add("rank", T.LongType()).add("id", T.LongType()))

    def _cut(self) -> list[int]:
        from ..operators.engine import pivot_select, pivot_sort

        judge = Judge(self.docs, LexicalRanker(self.query), RankParams())
        return pivot_sort(judge, pivot_select(judge, sorted(self.docs), self.k))

    def eval(self, row, query: str, k: int):
        self.query, self.k, self.scope = query, k, row["scope"]
        self.docs[row["id"]] = Doc(row["id"], row["text"])
        if len(self.docs) >= max(20, 2 * k):
            self.docs = {i: self.docs[i] for i in self._cut()}

    def terminate(self):
        for rank, i in enumerate(self._cut(), 1):
            yield self.scope, rank, i
