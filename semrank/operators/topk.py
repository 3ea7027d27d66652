"""Distributed tournament, multi-pivot select and sort, and bin filter.

Each runs level by level over all scopes at once. Once what is left of a scope (or of a segment of a sort) is small,
one task finishes it with the local engine: at most ``tail`` rows and ``TAIL_BYTES`` of text. That says where calls are
made, not which: results and ledger are the same for any ``tail``. Every level's calls are materialised once.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from functools import partial, reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..schema import CALLS, RankParams
from ..sources.tables import bound_batches, materialise
from . import columns
from .binning import assign_bins, shuffle_key
from .engine import SPREAD_SAMPLE, Doc, Judge, pairwise, pivot_select, pivot_sort, refine_top, tournament_topk
from .kernel import Ranked, counted, ledger_of, lists_of, named, rank_lists
from .rankers import ColumnRanker, Ranker, ReversedRanker

#: Rows and bytes of text that one task takes over.
TAIL, TAIL_BYTES = 20_000, 256 << 20
#: Rows that one task takes over where it holds them as arrays (``columns``), some 200 bytes each.
COLUMN_TAIL = 1 << 20
#: Documents and characters of text that a task of ``select_cross`` ranks at a time.
CROSS, CROSS_BYTES = 500, 8 << 20
#: More winners than any scope has documents.
ALL = 1 << 60
_CALL_FIELDS = [x.split(" ")[0] for x in CALLS.split(", ")]
_OUT = "scope bigint, seg bigint, rank bigint, id bigint, " + ", ".join(x for x in CALLS.split(", ") if not x.startswith("scope"))


def _finish(algo: str, judge: Judge, ids: list[int], k: int, beaten: dict[int, set[int]], turn: int, seg: int, step: int) -> tuple[list[int], bool]:
    """The local tail of an algorithm: ids and whether their order counts."""
    if algo == "tournament":
        return tournament_topk(judge, ids, k, beaten=beaten, step=step, seg=seg), True
    if algo == "select":
        return pivot_select(judge, ids, k, turn=turn), False
    if algo in ("sort", "refine"):
        return pivot_sort(judge, ids, turn=turn, seg=seg, phase=algo), True
    if algo == "pivot":
        return pivot_sort(judge, pivot_select(judge, ids, k)), True
    if algo == "all":
        return ids, False
    raise ValueError(algo)


def _frame(rows: list[dict], schema: str) -> pd.DataFrame:
    fields = [y.split(" ") for y in schema.split(", ")]
    frame = pd.DataFrame(rows, columns=[c for c, _ in fields])
    for c, kind in fields:
        frame[c] = frame[c].astype({"bigint": "Int64", "int": "Int32", "double": "Float64", "boolean": "boolean", "string": "object"}[kind])
    return frame


def run_local(items: DataFrame, algo: str, k: int, ranker: Ranker, params: RankParams, seed: int = 42, queries: DataFrame | None = None, refine: int = 0, sort_pivots: int | None = None, votes: int = 1, step: int = 0) -> Ranked:
    """One task per scope and segment. items may also have: seg and turn (where a run goes on), k (where scopes differ),
    better (the id known to be better, of a bracket that ran ``step`` levels). Ranks count from 1 in their segment."""
    if algo in ("select", "sort", "pivot", "tournament") and not step and _by_columns(algo, k, ranker, params, votes):
        return run_columns(items, algo, k, ranker, params, seed, refine, sort_pivots)
    run_id = uuid.uuid4().hex[:12]

    def own(name: str, other: Column) -> Column:
        return F.col(name) if name in items.columns else other.alias(name)

    zero, none = F.lit(0).cast("long"), F.lit(None).cast("long")
    x = items.select("scope", own("seg", zero), own("turn", F.lit(0)), own("k", F.lit(k)), own("better", none), "id", "payload", "score", "proxy")
    x = x.join(queries.select("scope", F.col("query").alias("_q")), "scope", "left") if queries is not None else x.withColumn("_q", F.lit(""))

    def run(part: pd.DataFrame) -> pd.DataFrame:
        scope, seg, turn, wanted = (int(part[c].iloc[0]) for c in ("scope", "seg", "turn", "k"))
        clean = part.astype(object).where(part.notna(), None)
        docs = {int(i): Doc(int(i), p, s, q) for i, p, s, q in zip(clean["id"], clean["payload"], clean["score"], clean["proxy"], strict=True)}
        beaten = {int(i): {int(b)} for i, b in zip(clean["id"], clean["better"], strict=True) if b is not None}
        judge, ids = Judge(docs, ranker, params, clean["_q"].iloc[0] or "", seed, scope, votes=votes), sorted(docs)
        if algo == "pivot" and sort_pivots:
            chosen = pivot_select(judge, ids, wanted)
            judge.params = params.but(pivots=sort_pivots, pivot_group=None, early_stop=False)
            got, ordered = pivot_sort(judge, chosen), True
        else:
            got, ordered = _finish(algo, judge, ids, wanted, beaten, turn, seg, step)
        if refine:
            got = refine_top(judge, got, refine)
        out = [{"scope": scope, "seg": seg, "rank": n if ordered else None, "id": i} for n, i in enumerate(got, 1)]
        return _frame([*out, *(c | {"run_id": run_id} for c in judge.calls)], _OUT)

    done = materialise(x.groupBy("scope", "seg").applyInPandas(run, _OUT), "tail")
    return Ranked(done.filter("call_id is null").select("scope", "seg", "rank", "id"), done.filter("call_id is not null").select(*_CALL_FIELDS))


def _by_columns(algo: str, k: int, ranker: Ranker, params: RankParams, votes: int = 1) -> bool:
    """Whether a task can finish a scope as arrays: a score column with noise, and few winners where those are ranked call by call."""
    few = {"tournament": params.list_size, "pivot": TAIL}.get(algo, k)
    return votes == 1 and columns.columnar(ranker) and k <= few and not (algo == "sort" and params.pivot_mode != "random")


def run_columns(items: DataFrame, algo: str, k: int, ranker: Ranker, params: RankParams, seed: int = 42, refine: int = 0, sort_pivots: int | None = None) -> Ranked:
    """``run_local`` for rankers of ``columns.columnar``: no texts are moved, and the ledger leaves the task in batches."""
    chars = F.coalesce(F.length("payload"), F.lit(0)).cast("long").alias("chars")
    given = [c for c in ("seg", "turn", "k") if c in items.columns]
    x = items.select("scope", *given, "id", "score", "proxy", chars)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = pa.Table.from_batches(list(batches)).combine_chunks()
        if part["id"].null_count:
            raise ValueError("a document to be ranked has no id")
        scope = part["scope"][0].as_py()
        seg, turn, wanted = (part[c][0].as_py() if c in given else other for c, other in (("seg", 0), ("turn", 0), ("k", k)))
        ids, scores, proxies, sizes = (part[c].to_numpy() for c in ("id", "score", "proxy", "chars"))
        del part
        t = columns.Table(ids, scores.astype(float), proxies.astype(float), sizes, ranker, params, seed, scope)
        del ids, scores, proxies, sizes
        late: list[dict] = []

        def judge(docs: np.ndarray, p: RankParams) -> Judge:
            """For the few documents that are ranked call by call. Texts stand for their length."""
            held = {int(t.ids[i]): Doc(int(t.ids[i]), "x" * int(t.chars[i]), float(t.scores[i]), float(t.proxies[i])) for i in docs}
            return Judge(held, ranker, p, "", seed, scope, late)

        if algo == "select":
            got = t.ids[(yield from columns.select(t, wanted, turn))]
        elif algo == "sort":
            got = t.ids[(yield from columns.sort(t, turn, seg))]
        elif algo == "bin_filter":
            got = t.ids[(yield from columns.filtered(t, params.survivors, turn))]
        elif algo == "tournament":
            docs, better, level = yield from columns.bracket(t, wanted, seg)
            beaten = {int(t.ids[i]): {int(t.ids[b])} for i, b in zip(docs, better, strict=True) if b >= 0}
            got = np.array(tournament_topk(judge(docs, params), t.ids[docs].tolist(), wanted, beaten=beaten, step=level, seg=seg), np.int64)
        else:
            docs = yield from columns.select(t, wanted)
            last = judge(docs, params.but(pivots=sort_pivots, pivot_group=None, early_stop=False) if sort_pivots else params)
            order = pivot_sort(last, t.ids[docs].tolist())
            got = np.array(refine_top(last, order, refine) if refine else order, np.int64)
        if late:
            yield pa.RecordBatch.from_pylist([{f: c.get(f) for f in columns.SCHEMA.names} for c in late], columns.SCHEMA)
        for at in range(0, len(got), columns.BATCH):
            ids = got[at : at + columns.BATCH]
            n = len(ids)
            known = {"scope": pa.array(np.full(n, scope)), "seg": pa.array(np.full(n, seg)), "id": pa.array(ids)}
            if algo not in ("select", "bin_filter"):
                known["rank"] = pa.array(np.arange(at + 1, at + n + 1))
            yield pa.RecordBatch.from_arrays([known.get(f.name, pa.nulls(n, f.type)) for f in columns.SCHEMA], schema=columns.SCHEMA)

    out = ", ".join(c for c in _OUT.split(", ") if c.split(" ")[0] in columns.SCHEMA.names)
    done = materialise(x.groupBy(*(c for c in ("scope", "seg") if c in x.columns)).applyInArrow(run, out), "tail")
    calls = done.filter("id is null").withColumns({"run_id": F.lit(uuid.uuid4().hex[:12]), "repaired": F.lit(False)})
    return Ranked(done.filter("id is not null").select("scope", "seg", "rank", "id"), calls.select(*_CALL_FIELDS))


def _lean(items: DataFrame, ranker: Ranker) -> DataFrame:
    """items without texts for a ranker that reads the score column only: no text is moved, held by a task or counted as sent."""
    return items.withColumn("payload", F.lit(None).cast("string")) if ranker.native else items


def _joined(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _sizes(items: DataFrame, *keys: str) -> DataFrame:
    """(keys, n, bytes): rows and bytes of text."""
    return items.groupBy(*(keys or ("scope",))).agg(F.count("*").alias("n"), F.coalesce(F.sum(F.octet_length("payload")), F.lit(0)).alias("bytes"))


def _large(params: RankParams, tail: int) -> Column:
    """Whether a scope of n documents and so many bytes is more than a task takes over; one list always fits."""
    return (F.col("n") > params.list_size) & ((F.col("n") > tail) | (F.col("bytes") > TAIL_BYTES))


def _tail(tail: int | None, *by: bool) -> int:
    """A caller's tail, or the one for how tasks finish scopes (``_by_columns``)."""
    return tail if tail is not None else COLUMN_TAIL if all(by) else TAIL


def bin_filter(items: DataFrame, ranker: Ranker, params: RankParams, seed: int = 42, rounds: int = 1, queries: DataFrame | None = None, mode: str | None = None, least: int = 0, votes: int = 1) -> Ranked:
    """The best S of every bin of L, ``rounds`` times. ``least``: survivors that a scope with that many documents must keep."""
    run_id, calls = uuid.uuid4().hex[:12], []
    arrays = _by_columns("bin_filter", 0, ranker, params, votes) and (mode or params.binning) == "exact"
    for turn in range(rounds):
        if arrays and not _sizes(items).filter(F.col("n") > COLUMN_TAIL).take(1):
            done = run_columns(items.withColumn("turn", F.lit(turn)), "bin_filter", 0, ranker, params, seed)
            calls.append(done.calls)
            kept = done.rows.select("scope", "id")
        else:
            lists = named(lists_of(assign_bins(items, params.list_size, seed, turn, mode=mode or params.binning), ["scope"], "bin"), "bin_filter", turn, F.col("bin"))
            done = materialise(counted(rank_lists(lists, ranker, queries, params, seed, votes)), "filter")
            calls.append(ledger_of(done, run_id, "bin_filter", turn))
            kept = done.select("scope", F.explode(F.slice("ranked", 1, params.survivors)).alias("d")).select("scope", F.col("d.id").alias("id"))
        items = items.join(kept, ["scope", "id"], "left_semi")
        if least and turn + 1 == rounds:
            short = _sizes(items).filter(F.col("n") < least).limit(1).collect()
            if short:
                raise ValueError(f"{params.survivors} survivors a bin leave {short[0]['n']} documents, fewer than {least}")
    return Ranked(items, _joined(calls))


def survivor_count(n: int, size: int, s: int) -> int:
    return s * (n // size) + min(s, n % size)


def tournament(items: DataFrame, k: int, ranker: Ranker, params: RankParams | None = None, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None, mode: str | None = None, votes: int = 1) -> Ranked:
    """Ordered top k. The first bracket's early levels are distributed; documents with k known betters are let go.

    What is left for one task are the documents with fewer than k known betters. Where that is still too much, since k is
    large, groups of documents hold tournaments of their own and their winners another one: the same result from a
    consistent ranker, for more calls. A k that even a group can't hold is refused: winners follow one another, so a
    tournament of that length belongs to ``tournament_sort``, ``sort`` or ``select``.
    """
    params = params or RankParams()
    tail = _tail(tail, _by_columns("tournament", k, ranker, params, votes))
    run_id, calls, level, items = uuid.uuid4().hex[:12], [], 0, items.select("scope", "id", "payload", "score", "proxy")
    live = items = _lean(items, ranker)
    tree = None
    # tree: (scope, id, root, depth, better) of the documents with fewer than k known betters; a head is its own root
    while True:
        sizes = _sizes(live)
        heads = sizes.select("scope", F.col("n").alias("heads")) if tree is None else tree.filter("depth = 0").groupBy("scope").agg(F.count("*").alias("heads"))
        most = sizes.join(heads, "scope").filter(_large(params, tail) & (F.col("heads") > 1)).agg(F.max("heads")).first()[0]
        if not most:
            break
        if tree is None:  # read at every level, so what made the items runs once
            live = items = materialise(items, "items")
            tail = min(tail, TAIL)  # a bracket that began here ends call by call
        # few heads that lie in many partitions would never meet inside them
        how = "exact" if level and most <= tail else mode or params.binning
        field_ = live if tree is None else live.join(tree.filter("depth = 0").select("scope", "id"), ["scope", "id"], "left_semi")
        binned = assign_bins(field_, params.list_size, seed, f"0.{level}", mode=how)
        lists = named(lists_of(binned, ["scope"], "bin"), "tournament", 0, F.concat(F.lit(f"{level}."), F.col("bin").cast("string")))
        done = materialise(counted(rank_lists(lists, ranker, queries, params, seed, votes)), "bracket")
        calls.append(ledger_of(done, run_id, "tournament", 0))
        placed = done.select("scope", F.posexplode(F.slice("ranked", 1, k)).alias("p", "d"), F.col("ranked.id").alias("ids"))
        placed = placed.select("scope", F.col("d.id").alias("id"), F.col("ids")[0].alias("head"), "p", F.expr("if(p > 0, get(ids, p - 1), null)").alias("lost_to"))
        if tree is None:
            tree = placed.select("scope", "id", F.col("head").alias("root"), F.col("p").alias("depth"), F.col("lost_to").alias("better"))
        else:
            above = placed.withColumnRenamed("id", "root")
            tree = tree.join(above, ["scope", "root"]).select("scope", "id", F.col("head").alias("root"), (F.col("depth") + F.col("p")).alias("depth"), F.coalesce("better", "lost_to").alias("better")).filter(F.col("depth") < k)
        tree = materialise(tree, "tree")
        live = items.join(tree.select("scope", "id"), ["scope", "id"], "left_semi")
        level += 1
    rest = items if tree is None else items.join(tree.select("scope", "id", "better"), ["scope", "id"])
    many = _sizes(rest).filter(_large(params, tail)).select("scope", "n")
    if tree is not None and (most := many.agg(F.max("n")).first()[0]):
        if 4 * k > tail:  # groups have a third of a tail at least, so that a quarter or more of the documents go each time
            raise ValueError(f"a tournament for {k} winners needs a tail of {4 * k} rows or more; sort and select don't")
        parts = many.select("scope", F.ceil(F.lit(2 * most) / F.lit(tail)).cast("long").alias("_parts"))
        split = items.join(parts, "scope", "left").withColumn("seg", F.pmod(F.xxhash64("id"), F.coalesce("_parts", F.lit(1))))
        names = split.select("scope", "seg").distinct().withColumn("_group", F.xxhash64("scope", "seg"))
        grouped = split.join(names, ["scope", "seg"]).select(F.col("_group").alias("scope"), "id", "payload", "score", "proxy")
        asks = None if queries is None else names.join(queries, "scope").select(F.col("_group").alias("scope"), "query")
        first = tournament(grouped, k, ranker, params, seed, asks, tail, mode, votes)
        back = names.select("scope", F.col("_group"))
        first_calls = first.calls.withColumnRenamed("scope", "_group").join(back, "_group").select(*_CALL_FIELDS)
        won = first.rows.withColumnRenamed("scope", "_group").join(back, "_group").select("scope", "id")
        last = tournament(items.join(won, ["scope", "id"], "left_semi"), k, ranker, params, seed + 1, queries, tail, mode, votes)
        return Ranked(last.rows, _joined([first_calls, last.calls]))
    done = run_local(rest, "tournament", k, ranker, params, seed, queries, votes=votes, step=level)
    return Ranked(done.rows.select("scope", "rank", "id"), _joined([*calls, done.calls]))


def _lead(items: DataFrame, keys: list[str], order: list, most: int, alias: str = "ix") -> DataFrame:
    """The first ``most`` rows of each key; Spark limits each task's rows before the exchange."""
    return items.withColumn(alias, F.row_number().over(W.partitionBy(*keys).orderBy(*order))).filter(F.col(alias) <= most)


def _deal(items: DataFrame, keys: list[str], ranker: Ranker, params: RankParams, seed: int, turn: int, run_id: str, algo: str, queries: DataFrame | None, wanted: DataFrame | None, votes: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """One round over all keys: (bucket of every document, pivots in settled order, ledger).

    wanted: (keys, remaining, n) for selection; with early stop the pivot groups are then asked one after the other.
    """
    seg = F.col("seg") if "seg" in keys else None
    plain, likely = [shuffle_key(seed, f"pivot{turn}"), "id"], [F.desc(F.coalesce("proxy", F.lit(0.0))), "id"]
    if params.pivot_mode == "random":
        pivots = _lead(items, keys, plain, params.pivots).drop("ix")
    elif wanted is not None:
        most = int(wanted.agg(F.max("remaining")).first()[0] or 0)
        first = F.greatest(F.lit(0), F.least(F.col("remaining") - 1, F.col("n") - params.pivots)) + 1
        near = _lead(items, keys, likely, most + params.pivots).join(wanted, keys)
        pivots = near.filter(F.col("ix").between(first, first + params.pivots - 1)).select(*items.columns)
    else:
        some = _lead(_lead(items, keys, plain, SPREAD_SAMPLE).drop("ix"), keys, likely, SPREAD_SAMPLE)
        some = some.withColumn("_m", F.count("*").over(W.partitionBy(*keys)))
        at = F.array(*(F.least(F.col("_m") - 1, F.floor(F.lit(j + 1) * F.col("_m") / F.lit(params.pivots + 1))) + 1 for j in range(params.pivots)))
        pivots = some.filter(F.array_contains(at, F.col("ix").cast("long"))).select(*items.columns)
    doc = F.struct("id", "payload", "score")
    lists = pivots.groupBy(*keys).agg(F.array_sort(F.collect_list(doc)).alias("docs")).select(*keys, F.lit(-1).cast("long").alias("bin"), F.lit("pivots").alias("kind"), F.lit(0).alias("n_pivots"), "docs")
    ordered = materialise(counted(rank_lists(named(lists, algo, turn, F.lit(""), seg), ranker, queries, params, seed, votes)), "pivots")
    calls = [ledger_of(ordered, run_id, algo, turn)]
    settled = ordered.select(*keys, F.col("ranked").alias("_settled"))
    picked = settled.select(*keys, F.posexplode("_settled").alias("ix", "d")).select(*keys, "ix", F.col("d.id").alias("id"))
    rest = items.join(picked, [*keys, "id"], "left_anti")
    groups = -(-params.pivots // params.group)
    stop = params.early_stop and wanted is not None
    buckets: list[DataFrame] = []
    asked, open_keys = rest, None
    for number in range(groups if stop else 1):
        own = asked if open_keys is None else asked.join(open_keys, keys, "left_semi")
        binned = assign_bins(own, params.list_size - params.group, seed, f"deal{turn}", keys, params.binning)
        dealt = lists_of(binned, keys, "bucket").join(settled, keys)
        if stop:
            dealt = dealt.withColumn("g", F.lit(number))
        else:
            dealt = dealt.withColumn("g", F.explode(F.sequence(F.lit(0), F.ceil(F.size("_settled") / F.lit(params.group)).cast("int") - 1)))
        dealt = dealt.withColumn("pv", F.expr(f"slice(_settled, g * {params.group} + 1, {params.group})")).filter(F.size("pv") > 0)
        dealt = named(dealt, algo, turn, F.concat_ws(".", F.col("g").cast("string"), F.col("bin").cast("string")), seg)
        dealt = dealt.withColumn("docs", F.concat("pv", "docs")).withColumn("n_pivots", F.size("pv")).withColumn("settled", F.col("pv.id")).drop("_settled", "pv")
        done = materialise(counted(rank_lists(dealt, ranker, queries, params, seed, votes)).withColumn("ranked", F.col("ranked.id")), "buckets")
        calls.append(ledger_of(done, run_id, algo, turn))
        # a document's bucket: how many of the list's pivots stand before it
        places = done.select(*keys, "g", "settled", F.transform("settled", lambda i: F.array_position("ranked", i)).alias("at"), F.posexplode("ranked").alias("p", "id"))
        each = places.filter(~F.array_contains("settled", F.col("id"))).select(*keys, "g", "id", F.size("settled").alias("m"), F.expr("aggregate(at, 0, (a, x) -> a + if(x <= p, 1, 0))").alias("b"))
        if not stop:
            buckets.append(each.groupBy(*keys, "id").agg(F.sum("b").cast("int").alias("bucket")).withColumn("groups", F.lit(groups)))
            break
        each = materialise(each, "each")
        base = number * params.group
        last = number + 1 == groups
        found = each if last else each.filter("b < m")
        buckets.append(found.select(*keys, "id", (F.col("b") + base).cast("int").alias("bucket"), F.lit(number + 1).alias("groups")))
        above = _joined(buckets).groupBy(*keys).agg(F.count("*").alias("c"))
        state = (own.select(*keys).distinct() if open_keys is None else open_keys).join(wanted, keys).join(above, keys, "left")
        open_now = materialise(state.filter(F.coalesce("c", F.lit(0)) + base + params.group < F.col("remaining")).select(*keys), "open")
        closed = each.filter("b = m").join(open_now, keys, "left_anti") if not last else each.filter("false")
        buckets.append(closed.select(*keys, "id", (F.col("b") + base).cast("int").alias("bucket"), F.lit(number + 1).alias("groups")))
        asked, open_keys = rest.join(each.filter("b = m").select(*keys, "id"), [*keys, "id"], "left_semi"), open_now
        if last or not open_now.take(1):
            break
    return materialise(_joined(buckets), "dealt"), picked, _joined(calls)


def select(items: DataFrame, k: int, ranker: Ranker, params: RankParams | None = None, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None, ascending: bool = False, votes: int = 1) -> Ranked:
    """The unordered top k of every scope (rank is null). ascending: the k worst, as the best under the ranker turned round."""
    params = params or RankParams()
    if ascending:
        items, ranker = turned(items, ranker)
    run_id, calls, taken, turn = uuid.uuid4().hex[:12], [], [], 0
    tail = _tail(tail, _by_columns("select", k, ranker, params, votes))
    if k <= 0:
        return Ranked(items.select("scope", F.lit(None).cast("long").alias("rank"), "id").limit(0), items.sparkSession.createDataFrame([], CALLS))
    cands = _lean(items, ranker).select("scope", "id", "payload", "score", "proxy")
    state = materialise(_sizes(cands).select("scope", F.least("n", F.lit(k)).alias("remaining"), "n", "bytes"), "state")
    small: list[DataFrame] = []
    large = _large(params, tail) & (F.col("remaining") < F.col("n"))
    if state.filter(large).take(1):
        cands = materialise(cands, "items")  # read several times in a round
    while state.filter(large).take(1):
        big = state.filter(large)
        small.append(cands.join(state.filter(~large).select("scope", F.col("remaining").alias("k")), "scope").withColumn("turn", F.lit(turn)))
        own = cands.join(big.select("scope"), "scope", "left_semi")
        dealt, pivots, made = _deal(own, ["scope"], ranker, params, seed, turn, run_id, "select", queries, big.select("scope", "remaining", "n"), votes)
        calls.append(made)
        # places in order: bucket 0, pivot 0, bucket 1, ...; with early stop nothing below the groups that were asked matters
        reach = dealt.groupBy("scope").agg(F.max("groups").alias("g"))
        sizes = dealt.groupBy("scope", F.col("bucket").alias("at")).agg(F.count("*").alias("c")).select("scope", (F.col("at") * 2).alias("at"), "c")
        shown = pivots.join(reach, "scope").filter(F.col("ix") < F.col("g") * params.group)
        sizes = sizes.unionByName(shown.select("scope", (F.col("ix") * 2 + 1).alias("at"), F.lit(1).cast("long").alias("c")))
        w = W.partitionBy("scope").orderBy("at").rowsBetween(W.unboundedPreceding, 0)
        cut = materialise(sizes.withColumn("upto", F.sum("c").over(w)).join(big.select("scope", "remaining"), "scope"), "cut")
        whole = cut.filter("upto <= remaining").select("scope", "at")
        split = cut.filter("upto > remaining and upto - c < remaining").select("scope", "at", (F.col("remaining") - (F.col("upto") - F.col("c"))).alias("left"), "c")
        place = dealt.select("scope", "id", (F.col("bucket") * 2).alias("at")).unionByName(pivots.select("scope", "id", (F.col("ix") * 2 + 1).alias("at")))
        taken.append(materialise(place.join(whole, ["scope", "at"]).select("scope", "id"), "taken"))
        # the split bucket goes on; pivots of groups that weren't asked lie in the last bucket
        inside = place.join(split, ["scope", "at"]).select("scope", "id")
        if params.early_stop:
            deep = split.join(reach, "scope").filter(F.col("at") == 2 * F.col("g") * params.group).select("scope")
            inside = inside.unionByName(pivots.join(reach, "scope").filter(F.col("ix") >= F.col("g") * params.group).join(deep, "scope", "left_semi").select("scope", "id"))
        cands = materialise(own.join(inside, ["scope", "id"], "left_semi"), "cands")
        state = materialise(_sizes(cands).join(split.select("scope", F.col("left").alias("remaining")), "scope").select("scope", "remaining", "n", "bytes"), "state")
        turn += 1
    small.append(cands.join(state.select("scope", F.col("remaining").alias("k")), "scope").withColumn("turn", F.lit(turn)))
    rest = run_local(_joined(small), "select", k, ranker, params, seed, queries, votes=votes)
    rows = _joined([x.select("scope", F.lit(None).cast("long").alias("rank"), "id") for x in taken] + [rest.rows.select("scope", "rank", "id")])
    return Ranked(rows, _joined([*calls, rest.calls]))


def select_cross(docs: DataFrame, queries: DataFrame, k: int, ranker: Ranker, params: RankParams | None = None, seed: int = 42) -> Ranked:
    """The unordered top k of every query over all documents (id, payload, score, proxy), without a row for each pair.

    A task goes through its documents in chunks and, for every query, selects the best k of a chunk and the k that it held
    before. The documents that some query holds at a task's end go on, each once, to fewer tasks, until one has them all.
    For a consistent ranker that is the top k of all. Queries go to every task whole. The ledger depends on how the
    documents lie; a call's name ends with its pass, task and chunk.
    """
    params, run_id = params or RankParams(), uuid.uuid4().hex[:12]
    asks = [(int(r["scope"]), r["query"] or "") for r in queries.select("scope", "query").distinct().collect()]
    schema = _OUT + ", payload string, score double, proxy double"
    bound_batches(docs.sparkSession)

    def run(turn: int, parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[int, list[int]] = {scope: [] for scope, _ in asks}
        known: dict[int, Doc] = {}
        task, number = TaskContext.get().partitionId(), 0

        def take(chunk: dict[int, Doc]) -> list[dict]:
            known.update(chunk)
            made = []
            for scope, query in asks:
                judge = Judge(known, ranker, params, query, seed, scope)
                held[scope] = pivot_select(judge, sorted({*held[scope], *chunk}), k)
                made += [c | {"run_id": run_id, "call_id": f"{c['call_id']}@{turn}.{task}.{number}"} for c in judge.calls]
            for i in known.keys() - set().union(*held.values()):
                del known[i]
            return made

        chunk, size = {}, 0
        for part in parts:
            clean = part.astype(object).where(part.notna(), None)
            for i, p, s, q in zip(clean["id"], clean["payload"], clean["score"], clean["proxy"], strict=True):
                chunk[int(i)] = Doc(int(i), p, s, q)
                size += len(p or "")
                if len(chunk) >= CROSS or size >= CROSS_BYTES:
                    yield _frame(take(chunk), schema)
                    chunk, size, number = {}, 0, number + 1
        if chunk:
            yield _frame(take(chunk), schema)
        yield _frame([{"scope": scope, "seg": task, "id": i} for scope, ids in held.items() for i in ids], schema)
        for d in known.values():
            yield _frame([{"id": d.id, "payload": d.payload, "score": d.score, "proxy": d.proxy}], schema)

    left, calls, turn = _lean(docs, ranker).select("id", "payload", "score", "proxy"), [], 0
    while True:
        done = materialise(left.mapInPandas(partial(run, turn), schema), "cross")
        calls.append(done.filter("call_id is not null").select(*_CALL_FIELDS))
        won = done.filter("call_id is null and scope is not null")
        tasks = won.select("seg").distinct().count()
        if tasks <= 1:
            return Ranked(won.select("scope", "rank", "id"), _joined(calls))
        left, turn = done.filter("scope is null").select("id", "payload", "score", "proxy").coalesce(-(-tasks // 8)), turn + 1


def sort(items: DataFrame, ranker: Ranker, params: RankParams | None = None, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None, ascending: bool = False, votes: int = 1, finish: str = "sort") -> Ranked:
    """All documents of every scope in order. Every segment of a level is dealt in the same job; positions come from counts.
    finish: how a task orders a segment that it takes over, by pivots (sort) or by a tournament for all its documents."""
    params = params or RankParams(pivots=6)
    if ascending:
        items, ranker = turned(items, ranker)
    run_id, calls, turn = uuid.uuid4().hex[:12], [], 0
    tail = _tail(tail, finish == "sort" and _by_columns("sort", 0, ranker, params, votes))
    items = _lean(items, ranker).select("scope", "id", "payload", "score", "proxy")
    # a segment is named by the number of documents before it, and has the turn at which it came to be
    segs = items.withColumns({"seg": F.lit(0).cast("long"), "turn": F.lit(0)})
    while True:
        big = materialise(_sizes(segs, "scope", "seg").filter(_large(params, tail)).select("scope", "seg"), "big")
        if not big.take(1):
            break
        segs = segs if turn else materialise(segs, "segments")
        own = segs.join(big, ["scope", "seg"], "left_semi")
        dealt, pivots, made = _deal(own.drop("turn"), ["scope", "seg"], ranker, params, seed, turn, run_id, "sort", queries, None, votes)
        calls.append(made)
        place = dealt.select("scope", "seg", "id", (F.col("bucket") * 2).alias("at")).unionByName(pivots.select("scope", "seg", "id", (F.col("ix") * 2 + 1).alias("at")))
        counts = place.groupBy("scope", "seg", "at").agg(F.count("*").alias("c"))
        w = W.partitionBy("scope", "seg").orderBy("at").rowsBetween(W.unboundedPreceding, -1)
        starts = counts.withColumn("start", F.col("seg") + F.coalesce(F.sum("c").over(w), F.lit(0))).drop("c")
        new = place.join(starts, ["scope", "seg", "at"]).select("scope", "id", F.col("start").alias("new"))
        moved = segs.join(new, ["scope", "id"], "left").withColumns({"turn": F.when(F.col("new").isNull(), F.col("turn")).otherwise(F.lit(turn + 1)), "seg": F.coalesce("new", "seg")}).drop("new")
        segs = materialise(moved, "segments")
        turn += 1
    rest = run_local(segs, finish, ALL, ranker, params, seed, queries, votes=votes)
    return Ranked(rest.rows.select("scope", (F.col("rank") + F.col("seg")).alias("rank"), "id"), _joined([*calls, rest.calls]))


def tournament_sort(items: DataFrame, ranker: Ranker, params: RankParams | None = None, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None, ascending: bool = False, votes: int = 1) -> Ranked:
    """All documents of every scope in order, by tournaments. Winners follow one another, so a scope that a task can't hold is
    first cut by pivots into segments of consecutive places; each holds a tournament of its own, all at the same time."""
    return sort(items, ranker, params, seed, queries, tail, ascending, votes, "tournament")


def pivot_topk(items: DataFrame, k: int, ranker: Ranker, params: RankParams | None = None, seed: int = 42, queries: DataFrame | None = None, tail: int | None = None, refine: int = 0, sort_pivots: int | None = None, ascending: bool = False, votes: int = 1) -> Ranked:
    """Select, then sort the k that were selected; ``refine``: re-rank the first so many by pairs. Both are distributed where k is large."""
    params = params or RankParams()
    if ascending:
        items, ranker = turned(items, ranker)
    items = _lean(items, ranker)
    if not _sizes(items).filter(_large(params, _tail(tail, _by_columns("pivot", k, ranker, params, votes)))).take(1):
        done = run_local(items, "pivot", k, ranker, params, seed, queries, refine=refine, sort_pivots=sort_pivots, votes=votes)
        return Ranked(done.rows.select("scope", "rank", "id"), done.calls)
    chosen = select(items, k, ranker, params, seed, queries, tail, votes=votes)
    kept = items.join(chosen.rows.select("scope", "id"), ["scope", "id"], "left_semi")
    plan = params.but(pivots=sort_pivots, pivot_group=None, early_stop=False) if sort_pivots else params
    done = sort(kept, ranker, plan, seed, queries, tail, votes=votes)
    rows, calls = done.rows, chosen.calls.unionByName(done.calls)
    if refine:
        head = rows.filter(F.col("rank") <= refine).select("scope", "id")
        again = run_local(items.join(head, ["scope", "id"], "left_semi"), "refine", 0, ranker, pairwise(plan), seed, queries, votes=votes)
        rows = rows.filter(F.col("rank") > refine).unionByName(again.rows.select("scope", "rank", "id"))
        calls = calls.unionByName(again.calls)
    return Ranked(rows, calls)


def turned(items: DataFrame, ranker: Ranker) -> tuple[DataFrame, Ranker]:
    """Items and ranker for the worst instead of the best: negated scores and proxies for a score column, turned responses otherwise."""
    items = items.withColumns({"score": -F.col("score"), "proxy": -F.col("proxy")}) if ranker.native else items.withColumn("proxy", -F.col("proxy"))
    return items, ranker if ranker.native else ReversedRanker(ranker)


def exact_topk(items: DataFrame, k: int) -> DataFrame:
    """What an ideal ranker would give: ORDER BY score DESC, id LIMIT k, per scope."""
    w = W.partitionBy("scope").orderBy(F.desc("score"), "id")
    return items.withColumn("rank", F.row_number().over(w).cast("long")).filter(F.col("rank") <= k).select("scope", "rank", "id")


PERFECT = ColumnRanker()
