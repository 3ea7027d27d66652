"""The retriever ensemble without a row for each pair of query and document.

Texts are read once: a document's counts of query words and hashed slots are written in short form. Each task scores its
documents for every query and keeps those that can still be among the best; the ranks of the few that a query's best can
come from are counted against all documents in a second turn. Queries go to every task whole.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.tables import bound_batches, materialise

_WORD = re.compile("[a-z]+")
#: Every byte but a to z as a blank: what lies between is ``words`` of a text in UTF-8.
_LETTERS = bytes(c if 97 <= c <= 122 else 32 for c in range(256))
_LISTS = ("overlap", "bm25", "cosine")
#: Documents that a task scores at a time, and bits that number them.
CHUNK, CHUNK_BITS = 2048, 12
#: Words whose slots a task remembers.
KNOWN = 1 << 18


def words(text: str | None) -> list[str]:
    """``baselines.token_array`` of a text."""
    return _WORD.findall((text or "").lower())


def overlaps(queries: DataFrame, docs: DataFrame) -> DataFrame:
    """(scope, id, overlap) for every query and document: distinct query words that the document holds. Texts are read once and not moved."""
    texts: dict[int, list[str]] = {}
    for r in queries.select("scope", "query").collect():
        texts.setdefault(r["scope"], []).append(r["query"] or "")
    scopes = sorted(texts)
    held: dict[bytes, np.ndarray] = {}
    for q, scope in enumerate(scopes):
        for word in (w for text in texts[scope] for w in set(words(text))):
            held.setdefault(word.encode(), np.zeros(len(scopes), np.int64))[q] += 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.zeros((batch.num_rows, len(scopes)), np.int64)
            for row, text in zip(found, batch.column(1), strict=True):
                for word in held.keys() & set((text.as_py() or "").lower().encode().translate(_LETTERS).split()):
                    row += held[word]
            ids = np.repeat(batch.column(0).to_numpy(zero_copy_only=False), len(scopes))
            yield pa.RecordBatch.from_arrays([pa.array(np.tile(np.array(scopes, np.int64), batch.num_rows)), pa.array(ids), pa.array(found.ravel())], ["scope", "id", "overlap"])

    bound_batches(docs.sparkSession)
    return docs.select(F.col("id").cast("long").alias("id"), F.col("payload").cast("string").alias("payload")).mapInArrow(run, "scope bigint, id bigint, overlap bigint")


def _slot_of(dims: int):
    import xxhash

    known: dict[str, int] = {}

    def slot(word: str) -> int:
        if word not in known:
            if len(known) >= KNOWN:
                known.clear()
            raw = xxhash.xxh64_intdigest(word, seed=42)
            known[word] = (raw - (1 << 64) if raw >> 63 else raw) % dims  # as pmod(xxhash64(word), dims)
        return known[word]

    return slot


def _lists(values: list[np.ndarray]) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, values)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(values) if values else [], pa.int32()))


def count_words(docs: DataFrame, vocabulary: dict[str, int], dims: int) -> DataFrame:
    """(id, len, terms, tf, slots, sf): how many words a document has, and how often each of the vocabulary and of each slot."""
    bound_batches(docs.sparkSession)
    names = ["id", "len", "terms", "tf", "slots", "sf"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slot = _slot_of(dims)
        for batch in batches:
            size, cols = [], ([], [], [], [])
            for text in batch.column(1):
                counts = Counter(words(text.as_py()))
                size.append(sum(counts.values()))
                terms = sorted((vocabulary[w], n) for w, n in counts.items() if w in vocabulary)
                slots: dict[int, int] = {}
                for w, n in counts.items():
                    s = slot(w)
                    slots[s] = slots.get(s, 0) + n
                for col, values in zip(cols, (*_columns(terms), *_columns(sorted(slots.items()))), strict=True):
                    col.append(values)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(size, pa.int64()), *map(_lists, cols)], names)

    return docs.select(F.col("id").cast("long").alias("id"), F.col("payload").cast("string").alias("payload")).mapInArrow(run, "id bigint, len bigint, terms array<int>, tf array<int>, slots array<int>, sf array<int>")


def _columns(pairs: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    got = np.array(pairs, np.int32).reshape(-1, 2)
    return got[:, 0], got[:, 1]


def _one_row_each(counted: DataFrame) -> DataFrame:
    """Rows of one id (null is one too) as one document that has all their words; ids that occur once are neither moved nor written again."""
    again = materialise(counted.groupBy(F.col("id").alias("_id")).agg(F.count("*").alias("_n")).filter("_n > 1").select("_id"), "again")
    if again.isEmpty():
        return counted

    def entries(kind: int, at: str, n: str):
        return F.transform(F.arrays_zip(at, n), lambda x: F.struct(F.lit(kind).alias("kind"), x[at].alias("at"), x[n].cast("long").alias("n")))

    def summed(kind: int):
        return F.sort_array(F.collect_list(F.when(F.col("kind") == kind, F.struct("at", "n"))))

    same = F.col("id").eqNullSafe(F.col("_id"))
    size = F.array(F.struct(F.lit(0).alias("kind"), F.lit(0).alias("at"), F.col("len").alias("n")))
    rows = counted.join(again, same, "left_semi").select("id", F.explode(F.concat(size, entries(1, "terms", "tf"), entries(2, "slots", "sf"))).alias("x"))
    sums = rows.groupBy("id", "x.kind", "x.at").agg(F.sum("x.n").alias("n"))
    one = sums.groupBy("id").agg(F.sum(F.when(F.col("kind") == 0, F.col("n"))).alias("len"), summed(1).alias("t"), summed(2).alias("s"))
    merged = one.select("id", "len", *(F.col(x).cast("array<int>").alias(name) for x, name in (("t.at", "terms"), ("t.n", "tf"), ("s.at", "slots"), ("s.n", "sf"))))
    return materialise(counted.join(again, same, "left_anti").unionByName(merged), "counted")


def _counts_of(counted: DataFrame, n_terms: int, dims: int) -> tuple[int, int, int, np.ndarray, np.ndarray]:
    """Documents, those with words, their words, and in how many documents each term and each slot occurs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(3 + n_terms + dims, np.int64)
        for b in batches:
            size = b.column("len").to_numpy()
            total[:3] += len(size), np.count_nonzero(size), size.sum()
            total[3 : 3 + n_terms] += np.bincount(b.column("terms").flatten(), minlength=n_terms)
            total[3 + n_terms :] += np.bincount(b.column("slots").flatten(), minlength=dims)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(total[at])], ["at", "n"])

    total = np.zeros(3 + n_terms + dims, np.int64)
    for r in counted.mapInArrow(run, "at bigint, n bigint").groupBy("at").agg(F.sum("n").alias("n")).collect():
        total[r["at"]] = r["n"]
    return int(total[0]), int(total[1]), int(total[2]), total[3 : 3 + n_terms], total[3 + n_terms :]


class Scorer:
    """Keys of a chunk's documents for every query and retriever: the value in billionths, as it is rounded for ranks; -1 where there is none."""

    def __init__(self, asks: list[list[str]], vocabulary: dict[str, int], dims: int, k1: float, b: float):
        slot = _slot_of(dims)
        self.n_terms, self.dims, self.n_queries, self.k1, self.b = len(vocabulary), dims, len(asks), k1, b
        self.held = [(vocabulary[w], q, n) for q, texts in enumerate(asks) for w, n in Counter(w for t in texts for w in set(words(t))).items()]
        self.asked = [(s, q, n) for q, texts in enumerate(asks) for s, n in Counter(slot(w) for t in texts for w in words(t)).items()]

    def learn(self, n: int, n_worded: int, n_words: int, df: np.ndarray, sdf: np.ndarray) -> None:
        self.mean = n_words / max(1, n_worded)
        self.idf = np.log(1 + (n_worded - df + 0.5) / (df + 0.5))
        self.sidf = np.where(sdf > 0, np.log((1 + n) / (1 + sdf)), 0.0)
        self.everywhere = (sdf == n) & (n > 0)

    def ready(self) -> None:
        """The matrices, made by each task."""
        self.has = np.zeros((self.n_terms, self.n_queries))
        for t, q, n in self.held:
            self.has[t, q] = n
        self.wants = np.zeros((self.dims, self.n_queries))
        for s, q, n in self.asked:
            self.wants[s, q] = n
        # a slot that every document has weighs nothing, but makes a pair
        self.always = self.wants[self.everywhere].any(axis=0)
        self.wants *= self.sidf[:, None]
        self.used = np.flatnonzero(self.wants.any(axis=1))
        self.size = np.sqrt((self.wants**2).sum(axis=0))
        self.column = np.full(self.dims, -1)
        self.column[self.used] = np.arange(len(self.used))
        self.wants = self.wants[self.used]

    def keys(self, batch: pa.RecordBatch) -> np.ndarray:
        """(retriever, query, document)."""
        rows, size = batch.num_rows, batch.column("len").to_numpy()

        def flat(name: str, count: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            col = batch.column(name)
            at = np.repeat(np.arange(rows), np.diff(col.offsets.to_numpy()))
            return at, col.flatten().to_numpy(), batch.column(count).flatten().to_numpy().astype(float)

        doc, term, tf = flat("terms", "tf")
        x = np.zeros((rows, self.n_terms))
        x[doc, term] = 1
        overlap = x @ self.has
        x[doc, term] = self.idf[term] * tf * (self.k1 + 1) / (tf + self.k1 * (1 - self.b + self.b * size[doc] / self.mean))
        bm25 = x @ self.has
        doc, slot, sf = flat("slots", "sf")
        weight = sf * self.sidf[slot]
        norm = np.sqrt(np.bincount(doc, weight**2, minlength=rows))
        x = np.zeros((rows, len(self.used)))
        ours = self.column[slot] >= 0
        x[doc[ours], self.column[slot[ours]]] = weight[ours]
        dot, scale = x @ self.wants, norm[:, None] * self.size[None, :]
        cosine = np.divide(dot, scale, out=np.zeros_like(dot), where=scale > 0)
        found = [(overlap, overlap > 0), (bm25, overlap > 0), (cosine, (dot > 0) | self.always[None, :] & (size > 0)[:, None])]
        return np.stack([np.where(there, np.rint(v * 1e9).astype(np.int64), -1).T for v, there in found])


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for start in range(0, b.num_rows, CHUNK):
            yield b.slice(start, CHUNK)


def _first(keys: np.ndarray, ids: np.ndarray, most: int) -> np.ndarray:
    """Places of the first ``most`` present keys, largest first, ties by id."""
    at = np.flatnonzero(keys >= 0)
    if len(at) > most:
        least = np.partition(keys[at], len(at) - most)[len(at) - most]
        at = at[keys[at] >= least]
    return at[np.lexsort((ids[at], -keys[at]))][:most]


_CAND = "scope bigint, id bigint, k0 bigint, k1 bigint, k2 bigint"


def fused_best(queries: DataFrame, docs: DataFrame, n: int = 50, c: int = 60, dims: int = 4096, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """(scope, id, score): exactly ``reciprocal_rank_fusion`` of token overlap, BM25 and hashed term cosine over all pairs.

    A document that no retriever has among its first m scores at most 3 / (c + m + 1), and each of the first n of one list
    at least 1 / (c + n); with m = 2 c + 3 n the best n of a query are among the first m of some retriever. Their ranks in
    the other lists are counted over all documents. Rows of one id are one document that has
    all their words; what has no id counts in the words' statistics as one document, but is in no list. A null scope is a query too.
    """
    spark = docs.sparkSession
    texts: dict[int | None, list[str]] = {}
    for r in queries.select("scope", "query").collect():
        texts.setdefault(r["scope"], []).append(r["query"] or "")
    # from here to the end a query goes by its place in this list
    scopes = sorted(texts, key=lambda x: (x is None, x or 0))
    asks = [texts[s] for s in scopes]
    vocabulary = {w: i for i, w in enumerate(sorted({w for a in asks for t in a for w in words(t)}))}
    every = _one_row_each(materialise(count_words(docs, vocabulary, dims), "counted"))
    counted = every.filter("id is not null")
    scorer, most = Scorer(asks, vocabulary, dims, k1, b), 2 * c + 3 * n
    scorer.learn(*_counts_of(every, len(vocabulary), dims))
    lists, bits = range(len(_LISTS)), CHUNK_BITS

    def nominate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer.ready()
        held = [(np.zeros(0, np.int64), np.zeros((len(_LISTS), 0), np.int64)) for _ in scopes]
        for chunk in _chunks(batches):
            ids, keys = chunk.column("id").to_numpy(), scorer.keys(chunk)
            for q in range(len(scopes)):
                some = np.unique(np.concatenate([_first(keys[x, q], ids, most) for x in lists]))
                own, its = np.concatenate([held[q][0], ids[some]]), np.concatenate([held[q][1], keys[:, q, some]], axis=1)
                some = np.unique(np.concatenate([_first(its[x], own, most) for x in lists]))
                held[q] = own[some], its[:, some]
        for q, (own, its) in enumerate(held):
            if len(own):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), q)), pa.array(own), *(pa.array(its[x]) for x in lists)], ["scope", "id", "k0", "k1", "k2"])

    def narrow(part: pd.DataFrame) -> pd.DataFrame:
        """The documents that can be among the best n; r: the rank, 0 where it isn't known yet, -1 where the list hasn't the document."""
        ids, keys = part["id"].to_numpy(), part[["k0", "k1", "k2"]].to_numpy().T
        ranks = np.where(keys < 0, -1, 0)
        for x in lists:
            at = _first(keys[x], ids, most)
            ranks[x, at] = np.arange(1, len(at) + 1)
        least = np.where(ranks > 0, 1 / (c + np.maximum(ranks, 1)), 0).sum(axis=0)
        largest = least + (ranks == 0).sum(axis=0) / (c + most + 1)
        bar = np.sort(least)[-n] if len(least) > n else 0.0
        keep = (ranks > 0).any(axis=0) & (largest >= bar - 1e-8)
        return part[keep].assign(r0=ranks[0, keep], r1=ranks[1, keep], r2=ranks[2, keep])

    nominated = counted.mapInArrow(nominate, _CAND)
    cands = materialise(nominated.groupBy("scope").applyInPandas(narrow, f"{_CAND}, r0 bigint, r1 bigint, r2 bigint"), "cands")
    open_: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}
    asked = cands.filter("r0 = 0 or r1 = 0 or r2 = 0").toPandas()
    for q, part in asked.groupby("scope"):
        for x in lists:
            if len(own := part[part[f"r{x}"] == 0]):
                open_[x, q] = own["id"].to_numpy(), own[f"k{x}"].to_numpy()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """How many documents of the task stand before each candidate: keys and places by id as one number, which is sorted."""
        scorer.ready()
        before = {at: np.zeros(len(own), np.int64) for at, (own, _) in open_.items()}
        for chunk in _chunks(batches):
            ids, keys = chunk.column("id").to_numpy(), scorer.keys(chunk)
            by_id = np.sort(ids)
            place = np.searchsorted(by_id, ids)
            for (x, q), (own, its) in open_.items():
                line = np.sort((-keys[x, q] << bits) + place)
                before[x, q] += np.searchsorted(line, (-its << bits) + np.searchsorted(by_id, own))
        for (x, q), (own, _) in open_.items():
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), q)), pa.array(own), pa.array(np.full(len(own), x)), pa.array(before[x, q])], ["scope", "id", "list", "n"])

    known = F.explode(F.array(*(F.struct(F.lit(x).cast("long").alias("list"), F.col(f"r{x}").alias("r")) for x in lists)))
    ranks = cands.select("scope", "id", known.alias("v")).select("scope", "id", "v.list", "v.r").filter("r > 0")
    if open_:
        seen = counted.mapInArrow(count, "scope bigint, id bigint, list bigint, n bigint").groupBy("scope", "id", "list").agg(F.sum("n").alias("n"))
        ranks = ranks.unionByName(seen.select("scope", "id", "list", (F.col("n") + 1).alias("r")))
    fused = ranks.groupBy("scope", "id").agg(F.round(F.sum(1 / (c + F.col("r"))), 9).alias("score"))
    w = W.partitionBy("scope").orderBy(F.desc("score"), "id")
    best = fused.withColumn("_at", F.row_number().over(w)).filter(F.col("_at") <= n).withColumnRenamed("scope", "_q")
    named = spark.createDataFrame(list(enumerate(scopes)), "_q bigint, scope bigint")
    return best.join(F.broadcast(named), "_q").select("scope", "id", "score")
