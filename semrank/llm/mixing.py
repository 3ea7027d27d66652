"""Mixing sources to target weights: hierarchical budgets over a domain-language-source tree. DataFrame functions only.

A total budget of tokens flows down the tree. At every node the children share it by their weights; a child takes at
most what its leaves can give (their tokens times ``max_epochs``), and what it can't take goes to its siblings first.
Because a child's limit is that of its whole subtree, what a group of siblings can't take has already gone to their
parent's siblings, and so on up. A leaf whose budget is b takes whole epochs of its documents and then the shortest
prefix of one seeded order that fills the rest; the last document may pass the budget.

Prefixes are found by digits of the hash that orders the documents (of seed, doc_id and text): token sums by leaf and
first byte say in which byte the cut lies, sums by the second byte narrow it, and only that sliver is sorted, after rows
that are equal in all of it have been added up. No leaf, however large, is sorted or held by one task, nor are rows that
share a null or repeated doc_id. Texts never move: what is decided is a row per leaf and the sliver's rows, and every
document looks itself up.

Cases: a null or wordless text has 0 tokens and is never needed to fill a budget; null lang or source are branches of
their own; rows equal in doc_id, text, lang and source are taken together or not at all; no weights mean equal weights;
a weight that is null, zero or negative gives its branch nothing; other columns are ignored or, where documents are
returned, kept; a number of any length may end a source; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import stored

LEVELS = ("domain", "lang", "source")
#: Weights of domains and languages; branches not named here get weight 1.
DOMAIN_WEIGHTS = {"d0": 4.0, "d1": 3.0, "d2": 2.0, "d3": 1.0}
LANG_WEIGHTS = {"en": 5.0, "de": 2.0, "fr": 2.0, "es": 1.0}


def domain_of(source: Column) -> Column:
    """Sources belong to one of four domains by their number, of which the last two digits decide; a source without a number to a domain of its own."""
    number = F.regexp_extract(source, "([0-9]{1,2})$", 1)
    return F.when(F.coalesce(number, F.lit("")) == "", F.lit("dx")).otherwise(F.concat(F.lit("d"), F.pmod(number.cast("int"), F.lit(4)).cast("string")))


def token_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit("[^\\x20\\x09-\\x0D]+")), F.lit(0)).cast("long")


def _weight(level: Column, weights: dict[str, float] | None) -> Column:
    """The weight of a branch by its name; one that the mapping doesn't name has 1."""
    out = F.lit(1.0)
    for name, w in (weights or {}).items():
        out = F.when(level == name, F.lit(float(w or 0.0))).otherwise(out)
    return out


def shared_out(children: DataFrame, parent: list[str], order: str) -> DataFrame:
    """Adds ``budget``: the parent's ``parent_budget`` by ``weight``, none above ``capacity``; the surplus goes to siblings.

    The level of water: children sorted by capacity per weight; those below the level are full, the rest get it times their weight.
    """
    live = F.when((F.col("weight") > 0) & (F.col("capacity") > 0), F.col("capacity") / F.col("weight"))
    w = W.partitionBy(*parent).orderBy(F.col("ratio").asc_nulls_last(), F.col(order).asc_nulls_first())
    before, after = w.rowsBetween(W.unboundedPreceding, -1), w.rowsBetween(0, W.unboundedFollowing)
    x = children.withColumn("ratio", live)
    x = x.withColumn("level", (F.col("parent_budget") - F.coalesce(F.sum(F.when(F.col("ratio").isNotNull(), F.col("capacity"))).over(before), F.lit(0.0))) / F.sum(F.when(F.col("ratio").isNotNull(), F.col("weight"))).over(after))
    # full while the level at the own place is above the own ratio; the first that isn't sets the level for all after it
    x = x.withColumn("stop", F.max(F.when(F.col("ratio") > F.col("level"), F.col("level"))).over(W.partitionBy(*parent)))
    full = F.col("ratio") <= F.col("level")
    return x.withColumn("budget", F.when(F.col("ratio").isNull(), F.lit(0.0)).when(full, F.col("capacity")).otherwise(F.col("stop") * F.col("weight"))).drop("ratio", "level", "stop")


def budgets(leaves: DataFrame, total: Column, max_epochs: int, domain_weights=None, lang_weights=None, source_weights=None) -> DataFrame:
    """leaves (domain, lang, source, tokens) with capacity and budget. One row per leaf; windows run over siblings."""
    leaves = leaves.withColumn("capacity", (F.col("tokens") * max_epochs).cast("double"))
    budget = leaves.agg(total.cast("double").alias("parent_budget"), F.sum("capacity").alias("all"))
    out = budget.select(F.least("parent_budget", F.coalesce("all", F.lit(0.0))).alias("budget"))
    up: list[str] = []
    for level, weights in zip(LEVELS, (domain_weights, lang_weights, source_weights), strict=True):
        nodes = leaves.groupBy(*up, level).agg(F.sum("capacity").alias("capacity")).withColumn("weight", _weight(F.col(level), weights))
        parents = out.select(*(F.col(c).alias(f"p_{c}") for c in up), F.col("budget").alias("parent_budget"))
        match = [nodes[c].eqNullSafe(parents[f"p_{c}"]) for c in up]
        nodes = nodes.join(parents, match, "inner") if up else nodes.crossJoin(parents)
        out = shared_out(nodes.drop(*(f"p_{c}" for c in up)), up, level) if up else shared_out(nodes.withColumn("root", F.lit(0)), ["root"], level)
        up = [*up, level]
        out = out.select(*up, "capacity", F.round("budget", 3).alias("budget"))
    sizes = leaves.select(*(F.col(c).alias(f"p_{c}") for c in up), "tokens")
    return out.join(sizes, [out[c].eqNullSafe(sizes[f"p_{c}"]) for c in up]).select(*up, "tokens", "capacity", "budget")


_KEYS = ("doc_id", *LEVELS, "n_tokens", "row_hash", "order_key", "b1", "b2")


def _keyed(docs: DataFrame, seed: int, name) -> DataFrame:
    """``docs`` with the columns of _KEYS under the names that ``name`` gives them."""
    x = docs.withColumns({
        name("doc_id"): F.col("doc_id").cast("long"), name("domain"): domain_of(F.col("source").cast("string")), name("lang"): F.col("lang").cast("string"), name("source"): F.col("source").cast("string"),
        name("n_tokens"): token_count(F.col("text").cast("string")), name("row_hash"): F.md5(F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")),
    })
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col(name("doc_id")).cast("string"), F.lit("null")), F.col(name("row_hash"))).cast("binary"))
    x = x.withColumn(name("order_key"), key)
    return x.withColumns({name("b1"): F.substring(name("order_key"), 1, 2), name("b2"): F.substring(name("order_key"), 3, 2)})


def _decided(rows: DataFrame, total: Column, max_epochs: int, domain_weights, lang_weights, source_weights) -> tuple[DataFrame, DataFrame]:
    """(leaf, whole, c1, c2): a row per leaf; (leaf, order key, doc_id, row_hash) of the sliver's rows that are taken."""
    first = rows.groupBy(*LEVELS, "b1").agg(F.sum("n_tokens").alias("t"))
    leaves = first.groupBy(*LEVELS).agg(F.sum("t").alias("tokens"))
    plan = budgets(leaves, total, max_epochs, domain_weights, lang_weights, source_weights)
    plan = plan.select(*(F.col(c).alias(f"p_{c}") for c in LEVELS), F.floor(F.col("budget") / F.col("tokens")).cast("int").alias("whole"), "budget", "tokens")
    plan = plan.withColumn("rest", F.col("budget") - F.col("whole") * F.col("tokens"))
    plan = stored(plan.select(*(f"p_{c}" for c in LEVELS), "whole", "rest"), "mixing-plan")

    def of_leaf(x: DataFrame, y: DataFrame, how: str = "inner") -> DataFrame:
        return x.join(y, [x[c].eqNullSafe(y[f"p_{c}"]) for c in LEVELS], how)

    # where the cut lies: first byte, then second byte, then single documents
    w = W.partitionBy(*LEVELS).orderBy("b1").rowsBetween(W.unboundedPreceding, -1)
    cut1 = of_leaf(first.withColumn("before", F.coalesce(F.sum("t").over(w), F.lit(0))), plan).filter((F.col("before") < F.col("rest")) & (F.col("before") + F.col("t") >= F.col("rest")))
    cut1 = cut1.select(*(f"p_{c}" for c in LEVELS), F.col("b1").alias("c1"), "before", "rest")
    second = of_leaf(rows, cut1).filter(F.col("b1") == F.col("c1")).groupBy(*LEVELS, "c1", "before", "rest", "b2").agg(F.sum("n_tokens").alias("t"))
    w = W.partitionBy(*LEVELS).orderBy("b2").rowsBetween(W.unboundedPreceding, -1)
    cut2 = second.withColumn("at", F.col("before") + F.coalesce(F.sum("t").over(w), F.lit(0))).filter((F.col("at") < F.col("rest")) & (F.col("at") + F.col("t") >= F.col("rest")))
    cut2 = stored(cut2.select(*(F.col(c).alias(f"p_{c}") for c in LEVELS), "c1", F.col("b2").alias("c2"), F.col("at").alias("before"), "rest"), "mixing-cut")
    # rows equal in all of it stand for one another and are one here
    sliver = of_leaf(rows, cut2).filter((F.col("b1") == F.col("c1")) & (F.col("b2") == F.col("c2")))
    sliver = sliver.groupBy(*LEVELS, "order_key", "doc_id", "row_hash").agg(F.sum("n_tokens").alias("t"), F.max("before").alias("before"), F.max("rest").alias("rest"))
    w = W.partitionBy(*LEVELS).orderBy("order_key", F.col("doc_id").asc_nulls_first(), "row_hash").rowsBetween(W.unboundedPreceding, -1)
    last = sliver.withColumn("at", F.col("before") + F.coalesce(F.sum("t").over(w), F.lit(0))).filter("at < rest")
    last = stored(last.select(*(F.col(c).alias(f"l_{c}") for c in LEVELS), F.col("order_key").alias("l_key"), F.col("doc_id").alias("l_id"), F.col("row_hash").alias("l_hash")), "mixing-last")
    cuts = cut2.select(*(F.col(f"p_{c}").alias(f"c_{c}") for c in LEVELS), "c1", "c2")
    known = plan.join(cuts, [plan[f"p_{c}"].eqNullSafe(cuts[f"c_{c}"]) for c in LEVELS], "left").select(*(f"p_{c}" for c in LEVELS), "whole", "c1", "c2")
    return stored(known, "mixing-leaves"), last


def _epochs(keyed: DataFrame, name, known: DataFrame, last: DataFrame, out: str) -> DataFrame:
    """``keyed`` and column ``out``: how often each row is taken. Both tables are small beside the corpus; Spark broadcasts them if they are small at all."""
    known = known.select(*(F.col(c).alias(name(c)) for c in known.columns))
    last = last.select(*(F.col(c).alias(name(c)) for c in last.columns))
    x = keyed.join(known, [keyed[name(c)].eqNullSafe(known[name(f"p_{c}")]) for c in LEVELS])
    match = [keyed[name(c)].eqNullSafe(last[name(f"l_{c}")]) for c in LEVELS]
    x = x.join(last, [*match, keyed[name("order_key")] == last[name("l_key")], keyed[name("doc_id")].eqNullSafe(last[name("l_id")]), keyed[name("row_hash")] == last[name("l_hash")]], "left")
    b1, b2, c1, c2 = (F.col(name(c)) for c in ("b1", "b2", "c1", "c2"))
    in_prefix = c1.isNotNull() & ((b1 < c1) | ((b1 == c1) & (b2 < c2)) | F.col(name("l_key")).isNotNull())
    return x.withColumn(out, F.col(name("whole")) + F.when(in_prefix, F.lit(1)).otherwise(F.lit(0)))


def mixed(docs: DataFrame, total: Column, max_epochs: int = 2, seed: int = 42, domain_weights=None, lang_weights=None, source_weights=None) -> DataFrame:
    """(doc_id, row_hash, domain, lang, source, n_tokens, epochs) of the documents taken; epochs is how often each is taken.

    total: a column over the leaves' aggregate, such as F.lit(1e9) or 0.5 * F.sum("tokens").
    """
    same = lambda c: c
    rows = stored(_keyed(docs.select("doc_id", "lang", "source", "text"), seed, same).filter("n_tokens > 0").select(*_KEYS), "mixing")
    known, last = _decided(rows, total, max_epochs, domain_weights, lang_weights, source_weights)
    return _epochs(rows, same, known, last, "epochs").filter("epochs > 0").select("doc_id", "row_hash", *LEVELS, "n_tokens", "epochs")


def mixed_documents(docs: DataFrame, total: Column, seed: int = 42, domain_weights=None, lang_weights=None, source_weights=None) -> DataFrame:
    """The rows of ``docs`` that are taken, all columns, once each (at most one epoch). A text isn't exchanged."""
    same = lambda c: c
    rows = stored(_keyed(docs.select("doc_id", "lang", "source", "text"), seed, same).filter("n_tokens > 0").select(*_KEYS), "mixing")
    known, last = _decided(rows, total, 1, domain_weights, lang_weights, source_weights)
    prefix = "mix_"
    while any(c.lower().startswith(prefix) for c in docs.columns):
        prefix = "_" + prefix
    name = lambda c: prefix + c
    keyed = _keyed(docs, seed, name).filter(F.col(name("n_tokens")) > 0)
    return _epochs(keyed, name, known, last, name("epochs")).filter(F.col(name("epochs")) > 0).select(*(F.col(f"`{c}`") for c in docs.columns))


def mixing_sql(share: float, max_epochs: int, seed: int) -> str:
    """The same selection for DuckDB: budgets by level of water, prefixes by a running sum over all documents of a leaf."""

    def case(column: str, weights: dict[str, float]) -> str:
        return f"CASE {column} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in weights.items()) + " ELSE 1.0 END"

    def water(name: str, up: str, keys: str, weight: str, source: str) -> str:
        part, last = f"PARTITION BY {up}" if up else "PARTITION BY 1", keys.split(", ")[-1]
        return f"""
 {name}_w AS (SELECT *, capacity / weight AS ratio FROM (SELECT {keys}, capacity, parent_budget, {weight} AS weight FROM {source})),
 {name}_l AS (SELECT *, (parent_budget - coalesce(sum(capacity) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(weight) OVER (w ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM {name}_w WINDOW w AS ({part} ORDER BY ratio, {last} NULLS FIRST)),
 {name} AS (SELECT {keys}, round(CASE WHEN ratio <= level THEN capacity ELSE max(CASE WHEN ratio > level THEN level END) OVER ({part}) * weight END, 3) AS budget FROM {name}_l)"""

    return f"""WITH rows_ AS (SELECT doc_id, CASE WHEN regexp_extract(source, '([0-9]+)$', 1) = '' OR source IS NULL THEN 'dx' ELSE 'd' || (CAST(right(regexp_extract(source, '([0-9]+)$', 1), 2) AS BIGINT) % 4) END AS domain, lang, source,
  len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')) AS n_tokens, md5(coalesce(text, '')) AS row_hash, md5('{seed}:' || coalesce(CAST(doc_id AS VARCHAR), 'null') || ':' || md5(coalesce(text, ''))) AS order_key FROM documents),
 docs_ AS (SELECT * FROM rows_ WHERE n_tokens > 0),
 leaves AS (SELECT domain, lang, source, sum(n_tokens) AS tokens, CAST(sum(n_tokens) * {max_epochs} AS DOUBLE) AS capacity FROM docs_ GROUP BY ALL),
 total AS (SELECT least(CAST({share} * sum(tokens) AS DOUBLE), sum(capacity)) AS parent_budget FROM leaves),
 n1 AS (SELECT domain, sum(capacity) AS capacity, any_value(parent_budget) AS parent_budget FROM leaves, total GROUP BY domain),{water("b1", "", "domain", case("domain", DOMAIN_WEIGHTS), "n1")},
 n2 AS (SELECT l.domain, lang, sum(capacity) AS capacity, any_value(budget) AS parent_budget FROM leaves l JOIN b1 ON l.domain = b1.domain GROUP BY l.domain, lang),{water("b2", "domain", "domain, lang", case("lang", LANG_WEIGHTS), "n2")},
 n3 AS (SELECT l.domain, l.lang, source, sum(capacity) AS capacity, any_value(budget) AS parent_budget FROM leaves l JOIN b2 ON l.domain = b2.domain AND l.lang IS NOT DISTINCT FROM b2.lang GROUP BY l.domain, l.lang, source),{water("b3", "domain, lang", "domain, lang, source", "1.0", "n3")},
 plan AS (SELECT b3.*, floor(budget / tokens) AS whole, budget - floor(budget / tokens) * tokens AS rest FROM b3 JOIN leaves l ON b3.domain = l.domain AND b3.lang IS NOT DISTINCT FROM l.lang AND b3.source IS NOT DISTINCT FROM l.source),
 placed AS (SELECT d.*, whole, rest, sum(n_tokens) OVER (PARTITION BY d.domain, d.lang, d.source ORDER BY order_key, d.doc_id NULLS FIRST, row_hash ROWS UNBOUNDED PRECEDING) - n_tokens AS ahead FROM docs_ d JOIN plan p ON d.domain = p.domain AND d.lang IS NOT DISTINCT FROM p.lang AND d.source IS NOT DISTINCT FROM p.source)
SELECT doc_id, row_hash, domain, lang, source, n_tokens, CAST(whole + CASE WHEN ahead < rest THEN 1 ELSE 0 END AS INT) AS epochs FROM placed WHERE whole > 0 OR ahead < rest"""
