"""Line deduplication through a sharded minimal perfect hash.

A first pass counts, per distinct line hash (128 bits), the documents that hold the line and the largest
doc_id among them. Hashes found in ``min_docs`` documents go into shards; each shard is a minimal perfect
hash (hash, displace and compress: every bucket of keys stores the one seed under which its keys fall on
free slots) over compact arrays: fingerprints (the second 64 bits of the hash), counts and last holders.
The lines of documents then travel as 16-byte hashes to their shard and read one slot each; no table of
lines is joined. A shard that many documents ask is asked in several parts, of a size that its own counts give.

Cases: a null or empty text is one empty line; a document's repeated line counts once; rows that share a
doc_id are one document, each row keeps its own result row; a null doc_id is a document of its own, smaller
than any other; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import struct

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from .common import BLANKS, as_bytes, only, per_batch, stored

#: Keys per shard and probes per part of a shard aimed at; shards whose numbers of parts (12 bytes each) may be broadcast.
SHARD_KEYS, PART_PROBES, SENT_SHARDS = 32_768, 65_536, 1 << 20
_MIX1, _MIX2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def line_key(line: bytes) -> bytes:
    """The line without white space at its ends and with A-Z lower-cased."""
    return line.strip(BLANKS).lower()


def _code_points(key: bytes) -> int:
    return len(key) if key.isascii() else len(key.decode("utf-8", "replace"))


def row_hash(doc_id: int | None, text: bytes | None) -> int:
    return struct.unpack("<q", xxhash.xxh3_64_digest(text or b"", (doc_id or 0) & 0xFFFFFFFFFFFFFFFF))[0]


def hashed_lines(docs: DataFrame, min_chars: int) -> DataFrame:
    """(doc_id, row, h1, h2, pos) of every line long enough to count."""

    def make(batch: pa.RecordBatch) -> dict:
        ids, rows, h1, h2, at = [], [], [], [], []
        for doc_id, text in zip(batch.column(0).to_pylist(), as_bytes(batch), strict=True):
            row = None
            for pos, line in enumerate((text or b"").split(b"\n")):
                if len(line) >= min_chars and (len(key := line_key(line)) >= min_chars) and (key.isascii() or _code_points(key) >= min_chars):
                    row = row_hash(doc_id, text) if row is None else row
                    a, b = struct.unpack("<qq", xxhash.xxh3_128_digest(key))
                    ids.append(doc_id), rows.append(row), h1.append(a), h2.append(b), at.append(pos)
        return {"doc_id": ids, "row": rows, "h1": h1, "h2": h2, "pos": at}

    return per_batch(docs, make, "doc_id bigint, row bigint, h1 bigint, h2 bigint, pos int")


def _mixed(keys: np.ndarray, seed) -> np.ndarray:
    x = keys + np.asarray(seed, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(30))) * _MIX1
    x = (x ^ (x >> np.uint64(27))) * _MIX2
    return x ^ (x >> np.uint64(31))


class PerfectHash:
    """A minimal perfect hash over distinct 64-bit keys: slots 0..n-1, one seed per bucket of about four keys."""

    def __init__(self, n: int, seeds: np.ndarray):
        self.n, self.seeds = n, seeds

    @classmethod
    def of(cls, keys: np.ndarray) -> PerfectHash:
        n = len(keys)
        seeds = np.zeros(max(1, (n + 3) // 4), dtype=np.uint32)
        if not n:
            return cls(0, seeds)
        bucket = (_mixed(keys, 0) % np.uint64(len(seeds))).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        starts = np.searchsorted(bucket[order], np.arange(len(seeds) + 1))
        free = np.ones(n, dtype=bool)
        tries = np.arange(1, 129, dtype=np.uint64)[:, None]
        for b in np.argsort(starts[:-1] - starts[1:], kind="stable"):  # the fullest buckets first
            own = keys[order[starts[b] : starts[b + 1]]]
            if not len(own):
                break
            base = 0
            while True:
                slots = (_mixed(own[None, :], tries + np.uint64(base)) % np.uint64(n)).astype(np.int64)
                good = free[slots].all(axis=1)
                if len(own) > 1:
                    good &= (np.diff(np.sort(slots, axis=1), axis=1) > 0).all(axis=1)
                if good.any():
                    i = int(np.argmax(good))
                    seeds[b] = base + i + 1
                    free[slots[i]] = False
                    break
                base += len(tries)
        return cls(n, seeds)

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """The slot of each key; a key that isn't a member gets the slot of some member."""
        seeds = self.seeds[(_mixed(keys, 0) % np.uint64(len(self.seeds))).astype(np.int64)].astype(np.uint64)
        return (_mixed(keys, seeds) % np.uint64(self.n)).astype(np.int64)


def _build_shard(part: pd.DataFrame) -> pd.DataFrame:
    """One row of arrays for a shard. Keys are unique by both halves; keys whose first halves clash are kept as a list of their own."""
    part = part.sort_values(["h1", "h2"])
    twice = part.h1.duplicated(keep="first").to_numpy()
    one, rest = part[~twice], part[twice]
    keys = one.h1.to_numpy().astype(np.int64).view(np.uint64)
    mph = PerfectHash.of(keys)
    at = mph.slots(keys)
    arrays = {}
    for name, kind in (("h1", "<i8"), ("h2", "<i8"), ("n_docs", "<i8"), ("last", "<i8")):
        arrays[name] = np.empty(mph.n, dtype=kind)
        arrays[name][at] = one[name].to_numpy()
    spare = rest[["h1", "h2", "n_docs", "last"]].to_numpy().astype("<i8")
    return pd.DataFrame({"shard": part.shard.iloc[:1], "seeds": [mph.seeds.astype("<u4").tobytes()], "prints": [arrays["h2"].tobytes()], "counts": [arrays["n_docs"].tobytes()], "lasts": [arrays["last"].tobytes()], "spare": [spare.tobytes()]})


def _probe(h1: np.ndarray, h2: np.ndarray, shard: pd.Series) -> tuple[np.ndarray, np.ndarray]:
    """(count, last holder) of each hash, 0 where the shard doesn't know it."""
    prints = np.frombuffer(shard.prints, "<i8")
    mph = PerfectHash(len(prints), np.frombuffer(shard.seeds, "<u4"))
    at = mph.slots(h1.view(np.uint64))
    known = prints[at] == h2
    count = np.where(known, np.frombuffer(shard.counts, "<i8")[at], 0)
    last = np.where(known, np.frombuffer(shard.lasts, "<i8")[at], 0)
    for a, b, n, m in np.frombuffer(shard.spare, "<i8").reshape(-1, 4):
        mine = (h1 == a) & (h2 == b)
        count, last = np.where(mine, n, count), np.where(mine, m, last)
    return count, last


def dropped_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """(doc_id, row, pos) of every line to drop."""
    spark, low = docs.sparkSession, -(2**63)
    # one row for each hash and document on the way to the counts, so the most frequent line is dealt out by its documents
    lines = hashed_lines(docs, min_chars)
    known = (
        lines.select("h1", "h2", F.coalesce("doc_id", F.lit(low)).alias("doc_id")).distinct()
        .groupBy("h1", "h2").agg(F.count("*").alias("n_docs"), F.max("doc_id").alias("last"))
    )
    seen = Observation()
    known = stored(known.observe(seen, F.coalesce(F.sum("n_docs"), F.lit(0)).alias("lines")).filter(F.col("n_docs") >= min_docs), "line-counts")
    n_keys, n_probes = known.count(), seen.get["lines"]
    if not n_keys:
        return spark.createDataFrame([], "doc_id bigint, row bigint, pos int")
    shards = max(32, 2 ** int(np.ceil(np.log2(max(1, n_keys / SHARD_KEYS, n_probes / PART_PROBES)))))
    known = known.withColumn("shard", F.pmod(F.shiftright("h1", 20), F.lit(shards)).cast("int"))
    built = known.groupBy("shard").applyInPandas(_build_shard, "shard int, seeds binary, prints binary, counts binary, lasts binary, spare binary")
    # parts of a shard: as many as the documents that hold its lines ask for; one row per shard, sent along while these are few
    share = max(256, min(PART_PROBES, n_probes // shards))
    parts = known.groupBy("shard").agg(F.ceil(F.sum("n_docs") / F.lit(share)).cast("int").alias("parts"))
    spread = built.join(parts, "shard").select("*", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))
    asked = (
        lines.withColumn("shard", F.pmod(F.shiftright("h1", 20), F.lit(shards)).cast("int"))
        .join(F.broadcast(parts) if shards <= SENT_SHARDS else parts, "shard")
        .withColumn("part", F.pmod(F.xxhash64("row", "pos"), F.col("parts")).cast("int"))
        .select("shard", "part", "doc_id", "row", "pos", "h1", "h2")
    )

    def look_up(probes: pd.DataFrame, shard: pd.DataFrame) -> pd.DataFrame:
        if not len(probes) or not len(shard):
            return pd.DataFrame({"doc_id": [], "row": [], "pos": []})
        count, last = _probe(probes.h1.to_numpy(np.int64), probes.h2.to_numpy(np.int64), shard.iloc[0])
        ids = probes.doc_id.fillna(low).to_numpy(np.int64) if probes.doc_id.dtype != np.int64 else probes.doc_id.to_numpy()
        return probes.loc[(count >= min_docs) & (ids != last), ["doc_id", "row", "pos"]]

    return asked.groupBy("shard", "part").cogroup(spread.groupBy("shard", "part")).applyInPandas(look_up, "doc_id bigint, row bigint, pos int")


def dedup_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3) -> DataFrame:
    """doc_id, text (the lines that stay, joined by newlines), n_lines, n_dropped: one row per row of ``docs``."""
    docs = only(docs, "doc_id", "text")

    def rows(batch: pa.RecordBatch) -> dict:
        ids = batch.column(0).to_pylist()
        return {"doc_id": ids, "row": [row_hash(i, t) for i, t in zip(ids, as_bytes(batch), strict=True)], "text": batch.column(1)}

    keyed = per_batch(docs, rows, "doc_id bigint, row bigint, text string")
    drops = dropped_lines(docs, min_chars, min_docs).distinct().groupBy("row", "doc_id").agg(F.array_sort(F.collect_list("pos")).alias("drops"))
    cut = keyed.join(drops, (keyed["row"] == drops["row"]) & keyed["doc_id"].eqNullSafe(drops["doc_id"]), "left").select(keyed["doc_id"], "text", "drops")

    def keep(batch: pa.RecordBatch) -> dict:
        kept, n, gone = [], [], []
        for text, drops in zip(as_bytes(batch), batch.column(2).to_pylist(), strict=True):
            lines = (text or b"").split(b"\n")
            n.append(len(lines)), gone.append(len(drops or ()))
            out = set(drops or ())
            kept.append((b"\n".join(x for i, x in enumerate(lines) if i not in out) if out else text or b"").decode())
        return {"doc_id": batch.column(0), "text": kept, "n_lines": n, "n_dropped": gone}

    return per_batch(cut, keep, "doc_id bigint, text string, n_lines bigint, n_dropped bigint")
