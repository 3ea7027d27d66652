"""Benchmark decontamination with an FM-index per training shard.

Each task cuts its documents into shards of a few million bytes, maps words to the test vocabulary, keeps the
runs of test words (any other word can't be part of a match) and builds an FM-index over them. All test windows
of a block are searched backwards at once; occurrences are located through sampled suffix positions and merged
into removal spans per document. Documents never move, so there is no exchange at all.

The windows are the query set. They are held in blocks of ``BLOCK_BYTES`` of benchmark text as arrays (some nine bytes
for a byte of text), and only one block exists at a time, on the driver as on a worker: a benchmark of more than one
block takes a pass over the documents for each, written and read again in between.

Cases: a null or wordless text has no words and is clean; an item without words is never found; equal items
count each; an item without an id is named "null"; rows are handled one by one, so repeated rows give repeated results;
an empty benchmark finds nothing; columns of ``docs`` that have the names of the result's are replaced, unless ``prefix``
gives the result's other names; an item longer than a block is a block of its own.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .common import alnum_words, as_bytes, bounded_batches, enter, pa_schema, stored
from .fm_index import FMIndex

#: Bytes of text in a shard, and of benchmark text in a block that is sent to the tasks.
SHARD_BYTES, BLOCK_BYTES = 6_000_000, 4_000_000
FOUND = "n_words bigint, n_hit bigint, n_items bigint, items array<string>, starts array<bigint>, ends array<bigint>"


class Windows:
    """The test windows of a block of items: distinct windows as rows of symbols, and the items that each belongs to."""

    def __init__(self, items: list[tuple[object, bytes | None]], width: int):
        self.vocabulary: dict[bytes, int] = {}
        self.names = sorted({"null" if item is None else str(item) for item, _ in items})
        number = {name: i for i, name in enumerate(self.names)}
        rows, owners = [], []
        for item, text in items:
            ids = np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in alnum_words(text)], dtype=np.int32)
            if len(ids):
                own = np.lib.stride_tricks.sliding_window_view(ids, width) if len(ids) >= width else np.pad(ids, (0, width - len(ids)), constant_values=-1)[None, :]
                rows.append(own)
                owners.append(np.full(len(own), number["null" if item is None else str(item)], dtype=np.int32))
        every = np.ascontiguousarray(np.concatenate(rows) if rows else np.zeros((0, width), dtype=np.int32))
        owner = np.concatenate(owners) if owners else np.zeros(0, dtype=np.int32)
        # rows by their bytes: equal windows stand together, and each keeps its items once
        order = np.lexsort((owner, *every.T)) if len(every) else np.zeros(0, dtype=np.int64)
        every, owner = every[order], owner[order]
        new = np.concatenate(([True], (every[1:] != every[:-1]).any(axis=1))) if len(every) else np.zeros(0, dtype=bool)
        once = new | np.concatenate(([True], owner[1:] != owner[:-1])) if len(every) else new
        self.phrases, self.owner = every[new], owner[once]
        self.first = np.append(np.flatnonzero(new[once]), len(self.owner)).astype(np.int64)
        self.lengths = (self.phrases >= 0).sum(axis=1)
        self.shortest = int(self.lengths.min(initial=width))

    def items_of(self, windows: np.ndarray) -> list[str]:
        """The items of some windows, sorted as strings."""
        own = np.unique(windows)
        return [self.names[i] for i in np.unique(np.concatenate([self.owner[self.first[w] : self.first[w + 1]] for w in own]))]

    def search(self, texts: list[bytes | None]) -> list[tuple]:
        """(n_words, n_hit, n_items, items, span starts, span ends) of each text; spans are of words, ends excluded."""
        symbols, counts = [], []
        get = self.vocabulary.get
        for text in texts:
            words = alnum_words(text)
            counts.append(len(words))
            symbols.append(np.fromiter((get(w, 0) for w in words), dtype=np.int64, count=len(words)))
            symbols.append(np.zeros(1, dtype=np.int64))
        offsets = np.cumsum([0] + [c + 1 for c in counts])
        whole = np.concatenate(symbols) if symbols else np.zeros(0, dtype=np.int64)
        place, begin, owner = self._occurrences(whole)
        doc = np.searchsorted(offsets, begin, side="right") - 1
        order = np.lexsort((begin, doc))
        out, i = [], 0
        doc, begin, owner = doc[order], begin[order], owner[order]
        bounds = np.searchsorted(doc, np.arange(len(texts) + 1))
        for d, n in enumerate(counts):
            a, b = bounds[d], bounds[d + 1]
            if a == b:
                out.append((n, 0, 0, [], [], []))
                continue
            starts, ends = self._merged(begin[a:b] - offsets[d], self.lengths[owner[a:b]])
            items = self.items_of(owner[a:b])
            out.append((n, int((ends - starts).sum()), len(items), items, starts.tolist(), ends.tolist()))
        return out

    def _occurrences(self, whole: np.ndarray):
        """Places of every window in the sequence, as (row, start, window)."""
        none = np.zeros(0, dtype=np.int64)
        if not len(self.phrases):
            return none, none, none
        edge = np.flatnonzero(np.diff(np.concatenate(([0], (whole > 0).astype(np.int8), [0]))))
        starts, ends = edge[::2], edge[1::2]
        long = ends - starts >= self.shortest
        starts, ends = starts[long], ends[long]
        if not len(starts):
            return none, none, none
        size = ends - starts + 1  # each run and one separator
        base = np.concatenate(([0], np.cumsum(size)))
        source = np.arange(base[-1]) - np.repeat(base[:-1] - starts, size)
        kept = whole[source]
        kept[base[1:] - 1] = 0
        index = FMIndex(kept, len(self.vocabulary))
        low, high = index.ranges(self.phrases, self.lengths)
        found = high - low
        owner = np.repeat(np.arange(len(found)), found)
        rows = np.arange(found.sum()) - np.repeat(np.cumsum(found) - found, found) + np.repeat(low, found)
        return rows, source[index.locate(rows)], owner

    @staticmethod
    def _merged(starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Overlapping or touching spans as one; starts ascend."""
        reach = np.maximum.accumulate(starts + lengths)
        new = np.concatenate(([True], starts[1:] > reach[:-1]))
        at = np.flatnonzero(new)
        return starts[at], reach[np.concatenate((at[1:], [len(starts)])) - 1]


def _blocks(benchmark: DataFrame, id_col: str) -> Iterator[list[tuple]]:
    """The items in blocks of bounded size, one at a time; at least one block."""
    now, size, any_block = [], 0, False
    for item, text in benchmark.select(id_col, F.col("text").cast("binary")).orderBy(id_col).toLocalIterator():
        if now and size + len(text or b"") > BLOCK_BYTES:
            yield now
            now, size, any_block = [], 0, True
        now.append((item, None if text is None else bytes(text)))
        size += len(text or b"")
    if now or not any_block:
        yield now


def _together(old: tuple, new: tuple) -> tuple:
    """What two blocks found in one document."""
    if not old[1] or not new[1]:
        return old if old[1] else new
    spans = sorted((s, e) for p in (old, new) for s, e in zip(p[4], p[5], strict=True))
    s, e = Windows._merged(np.array([x[0] for x in spans]), np.array([x[1] - x[0] for x in spans]))
    items = sorted({*old[3], *new[3]})
    return (new[0], int((e - s).sum()), len(items), items, s.tolist(), e.tolist())


def find_leaks(docs: DataFrame, benchmark: DataFrame, width: int = 10, id_col: str = "item_id", prefix: str = "") -> DataFrame:
    """All columns of ``docs`` and those of FOUND (named with ``prefix``): word counts, items with occurrences, merged spans of words to remove."""
    spark = docs.sparkSession
    bounded_batches(spark)
    fields = StructType.fromDDL(", ".join(prefix + x for x in FOUND.split(", "))).fields
    names = [f.name for f in fields]
    taken = {n.lower() for n in names}
    plain = StructType([f for f in docs.schema.fields if f.name.lower() not in taken])
    docs, out = docs.select(*(F.col(f"`{f.name}`") for f in plain)), StructType([*plain.fields, *fields])
    blocks = _blocks(benchmark, id_col)
    block, number = next(blocks), 0
    while block is not None:
        tables, following = spark.sparkContext.broadcast(Windows(block, width)), next(blocks, None)
        docs = docs.mapInArrow(_searcher(tables, len(plain), out.names, names, number > 0), out)
        if following is not None:
            docs = stored(docs, "leaks")
            tables.destroy()
        block, number = following, number + 1
    return docs


def _searcher(tables, n_plain: int, out_names: list[str], names: list[str], again: bool):
    """Searches one block's windows in batches of documents; ``again``: the batches hold what earlier blocks found."""
    kinds = [f.type for f in pa_schema(FOUND)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("leaks")
        for batch in batches:
            texts, at = as_bytes(batch), 0
            while at < len(texts):
                end, size = at, 0
                while end < len(texts) and (end == at or size + len(texts[end] or b"") <= SHARD_BYTES):
                    size += len(texts[end] or b"")
                    end += 1
                found = tables.value.search(texts[at:end])
                if again:
                    before = zip(*(batch.column(n_plain + i).slice(at, end - at).to_pylist() for i in range(len(names))), strict=True)
                    found = [_together(x, y) for x, y in zip(before, found, strict=True)]
                columns = [batch.column(i).slice(at, end - at) for i in range(n_plain)]
                columns += [pa.array([f[i] for f in found], type=kinds[i]) for i in range(len(names))]
                yield pa.RecordBatch.from_arrays(columns, names=out_names)
                at = end

    return run


def items_digest(items) -> str:
    """sha2 over the sorted item ids, joined by commas, as a column."""
    return F.sha2(F.concat_ws(",", items).cast("binary"), 256)


def cut_spans(text: str | None, starts: list[int], ends: list[int]) -> str | None:
    """The text without the words of the spans and what stands between them."""
    import re

    if not text or not starts:
        return text
    words = [m.span() for m in re.finditer(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+", text)]
    out, at = [], 0
    for s, e in zip(starts, ends, strict=True):
        out.append(text[at : words[s][0]])
        at = words[e - 1][1]
    return "".join([*out, text[at:]])


def digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(items).encode()).hexdigest()
