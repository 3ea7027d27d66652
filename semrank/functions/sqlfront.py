"""SQL with a semantic sort: ``SELECT ... ORDER BY SEMANTIC('criterion' [, column]) [ASC | DESC] [LIMIT k]``."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .api import sem_order_by

_TAIL = re.compile(r"""ORDER\s+BY\s+SEMANTIC\s*\(\s*'((?:[^']|'')*)'\s*(?:,\s*([A-Za-z_]\w*)\s*)?\)\s*(ASC|DESC)?\s*(?:LIMIT\s+(\d+))?\s*;?\s*$""", re.IGNORECASE)


@dataclass(frozen=True)
class SemanticQuery:
    inner: str
    criterion: str
    column: str | None
    ascending: bool
    limit: int | None


def _top_level(sql: str) -> list[int]:
    """Places of ORDER outside of quotes, comments and parentheses."""
    out, depth, i = [], 0, 0
    while i < len(sql):
        c = sql[i]
        if c in "'\"`":
            i += 1
            while i < len(sql) and sql[i] != c:
                i += 1
        elif sql.startswith("--", i):
            i = sql.find("\n", i) if "\n" in sql[i:] else len(sql)
        elif c in "()":
            depth += 1 if c == "(" else -1
        elif depth == 0 and sql[i : i + 5].upper() == "ORDER" and (i == 0 or not (sql[i - 1].isalnum() or sql[i - 1] == "_")):
            out.append(i)
        i += 1
    return out


def parse(sql: str) -> SemanticQuery | None:
    """None for SQL without a semantic sort at its top level."""
    for at in reversed(_top_level(sql)):
        if m := _TAIL.match(sql, at):
            return SemanticQuery(sql[:at].rstrip(), m[1].replace("''", "'"), m[2], (m[3] or "").upper() == "ASC", int(m[4]) if m[4] else None)
    return None


def semantic_sql(spark: SparkSession, sql: str, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Runs the inner query in Spark, filters and all, and ranks only its result. Other SQL runs as it is. ASC asks for the least relevant."""
    q = parse(sql)
    if q is None:
        return spark.sql(sql)
    return sem_order_by(spark.sql(q.inner), q.column or text_col, q.criterion, id_col, q.limit, ascending=q.ascending, **options)
