"""Cross-entropy difference: how much more a document looks like target text than like the whole corpus.

Two bigram models, one of the target documents and one of all documents, share one vocabulary: every word of the
corpus. Words and bigrams are counted exactly, none is left out, however many there are; the background's counts are
scaled to the target's number of tokens, so the models are matched and differ in text only. A document's score is
its mean loss per token under the target model less that under the background model; lower is closer to the target.

Documents lie in chunks of some megabytes. A chunk counts its own words and bigrams and sends the counts, sorted by key
and cut into as many buckets as there are chunks, to those buckets that have any; a bucket adds up what has the same key
and sends the totals back in each chunk's order. So nothing of the corpus' size is on the driver or broadcast, and what is
kept and sent grows with the text: a chunk's rows are never more than its different words and bigrams. Larger chunks
(``chunk_bytes``) make fewer and longer rows where the corpus is very large, for more memory of a task. A key has 80 bits:
among three billion different words and bigrams (some 30 GB) the chance that any two share one is about 4 in a million.
``size`` and ``bits`` ask for bounded models instead: the most frequent words and ``2**bits`` hashed cells of bigrams.

Cases: a null or wordless text has no tokens and score 0; no target documents (or none with words) make all scores 0;
rows are scored one by one; a doc_id on several rows is a target on each; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, blank_words, bounded_batches, only, pa_schema, per_batch

VOCABULARY, BITS, STRENGTH, FLOOR = 65_536, 20, 50.0, 0.5
_FLUSH = 1_000_000
#: Bytes of text of one chunk; results don't depend on it.
CHUNK_BYTES = 8 << 20
#: Fixed values in place of words, which no word equals: what stands before a text's first word, and what marks a word's own count.
BEGIN, ONE = b"", b" "
_COUNTS = "chunk bigint, bucket bigint, n bigint, counts binary"
_TOTALS = "chunk bigint, bucket bigint, n bigint, totals binary"
_SIZES = "own_tokens bigint, all_tokens bigint, words bigint"
_ENTRY, _TOTAL = ("<u8", "<u2", "u1", "<i4", "<i4"), ("<i8", "<i8")
_SCORES = "doc_id bigint, n_tokens bigint, loss_target double, loss_background double, score double"


def vocabulary(docs: DataFrame, size: int = VOCABULARY) -> list[bytes]:
    """The most frequent words over all documents; ties by the word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = pa_schema("word binary, n bigint")
        counts: Counter = Counter()
        for batch in batches:
            for text in as_bytes(batch):
                counts.update(blank_words(text))
            if len(counts) > _FLUSH:
                yield pa.RecordBatch.from_pydict({"word": list(counts), "n": list(counts.values())}, schema=types)
                counts.clear()
        if counts:
            yield pa.RecordBatch.from_pydict({"word": list(counts), "n": list(counts.values())}, schema=types)

    totals = docs.select("text").mapInArrow(run, "word binary, n bigint").groupBy("word").agg(F.sum("n").alias("n"))
    return [bytes(w) for w in totals.orderBy(F.desc("n"), "word").limit(size).toArrow().column("word").to_pylist()]


def word_ids(text: bytes | None, known: dict[bytes, int]) -> np.ndarray:
    """0 stands for a word outside the vocabulary."""
    words = blank_words(text)
    get = known.get
    return np.fromiter((get(w, 0) for w in words), dtype=np.int64, count=len(words))


def cells(ids: np.ndarray, bits: int) -> np.ndarray:
    """The table cell of each bigram; the first word follows the unknown word."""
    before = np.concatenate(([0], ids[:-1])).astype(np.uint64)
    mixed = (before * np.uint64(0x9E3779B97F4A7C15) + ids.astype(np.uint64) + np.uint64(1)) * np.uint64(0xBF58476D1CE4E5B9)
    return (mixed >> np.uint64(64 - bits)).astype(np.int64)


def counted(docs: DataFrame, words: list[bytes], bits: int) -> np.ndarray:
    """Rows (target, all) of counts: first of words by id, then of bigram cells. docs: text and whether it is a target."""
    known = docs.sparkSession.sparkContext.broadcast({w: i + 1 for i, w in enumerate(words)})
    n, width = len(words) + 1, len(words) + 1 + 2**bits

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.zeros((2, width), dtype=np.int64)
        for batch in batches:
            for text, target in zip(as_bytes(batch), batch.column(1).to_pylist(), strict=True):
                ids = word_ids(text, known.value)
                if len(ids):
                    at = np.concatenate((ids, n + cells(ids, bits)))
                    np.add.at(table[1], at, 1)
                    if target:
                        np.add.at(table[0], at, 1)
        for start in range(0, width, 65_536):
            part = table[:, start : start + 65_536]
            used = np.flatnonzero(part[1])
            if len(used):
                yield pa.RecordBatch.from_arrays([pa.array((used + start).astype(np.int32)), pa.array(part[0][used]), pa.array(part[1][used])], names=["cell", "target", "every"])

    sums = docs.mapInArrow(run, "cell int, target bigint, every bigint").groupBy("cell").agg(F.sum("target").alias("target"), F.sum("every").alias("every")).toArrow()
    out = np.zeros((2, width), dtype=np.int64)
    at = sums.column("cell").to_numpy()
    out[0, at], out[1, at] = sums.column("target").to_numpy(), sums.column("every").to_numpy()
    return out


class Model:
    """A smoothed bigram model over counts of words and cells."""

    def __init__(self, counts: np.ndarray, n: int, scale: float, strength: float = STRENGTH):
        words, pairs = counts[:n] * scale, counts[n:] * scale
        total = words.sum()
        self.single = ((words + FLOOR) / (total + FLOOR * n)).astype(np.float32)
        self.words, self.pairs, self.strength = words.astype(np.float32), pairs.astype(np.float32), np.float32(strength)

    def losses(self, ids: np.ndarray, at: np.ndarray) -> np.ndarray:
        before = np.concatenate(([0], ids[:-1]))
        p = (self.pairs[at] + self.strength * self.single[ids]) / (self.words[before] + self.strength)
        return -np.log(np.minimum(p.astype(np.float64), 1.0))


def packed(columns: list[np.ndarray], kinds: tuple[str, ...], codec: pa.Codec) -> bytes:
    """Columns by planes of bytes, compressed: most counts are small."""
    planes = b"".join(c.astype(k).view(np.uint8).reshape(len(c), np.dtype(k).itemsize).T.tobytes() for c, k in zip(columns, kinds, strict=True))
    return codec.compress(planes, asbytes=True)


def unpacked(data: pa.Buffer, n: int, kinds: tuple[str, ...], codec: pa.Codec) -> list[np.ndarray]:
    planes = codec.decompress(data, n * sum(np.dtype(k).itemsize for k in kinds))
    out, at = [], 0
    for k in kinds:
        size = np.dtype(k).itemsize
        out.append(np.ascontiguousarray(np.frombuffer(planes, np.uint8, n * size, at).reshape(size, n).T).view(k).reshape(n))
        at += n * size
    return out


def zstd() -> pa.Codec:
    return pa.Codec("zstd", 1)


def mixed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = a * np.uint64(0x9E3779B97F4A7C15) + b
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(29))


class Chunk:
    """The words and bigrams of some texts. Entries, sorted by key: each word, BEGIN (counted by texts) and each bigram."""

    def __init__(self, texts: list[bytes | None]):
        places: defaultdict[bytes, int] = defaultdict()
        places.default_factory = places.__len__
        own = [np.fromiter(map(places.__getitem__, words), dtype=np.int64, count=len(words)) for words in map(blank_words, texts)]
        self.lengths = np.array([len(x) for x in own], dtype=np.int64)
        self.tokens = np.concatenate([np.zeros(0, dtype=np.int64), *own])
        self.n = len(places)
        # the places after the words' are those of BEGIN and ONE
        words = np.frombuffer(b"".join(blake2b(w, digest_size=16).digest() for w in (*places, BEGIN, ONE)), dtype="<u8").reshape(-1, 2)
        self.starts = (np.cumsum(self.lengths) - self.lengths)[self.lengths > 0]
        before = np.empty_like(self.tokens)
        before[1:] = self.tokens[:-1]
        before[self.starts] = self.n
        pairs, self.at = np.unique(before * (self.n + 1) + self.tokens, return_inverse=True)
        self.before, self.word = pairs // (self.n + 1), pairs % (self.n + 1)
        first = words[np.concatenate((np.full(self.n + 1, self.n + 1), self.before))]
        second = words[np.concatenate((np.arange(self.n + 1), self.word))]
        key, check = mixed(first[:, 0], second[:, 0]), mixed(first[:, 1], second[:, 1]) >> np.uint64(48)
        self.order = np.lexsort((check, key))
        self.key, self.check, self.is_word = key[self.order], check[self.order], self.order < self.n

    def counts(self, target: np.ndarray) -> list[np.ndarray]:
        """Counts (target, all) by entry."""
        out = []
        for told in (target, np.ones(len(target), dtype=bool)):
            kept = np.repeat(told, self.lengths)
            own = np.bincount(self.tokens[kept], minlength=self.n + 1)
            own[self.n] = (told & (self.lengths > 0)).sum()
            out.append(np.concatenate((own, np.bincount(self.at[kept], minlength=len(self.before))))[self.order])
        return out

    def bucket_starts(self, buckets: int) -> np.ndarray:
        return np.searchsorted(((self.key >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32), np.arange(buckets + 1, dtype=np.uint64))


def texts_of(docs: pa.Table) -> list[bytes | None]:
    return [t for batch in docs.select(["text"]).to_batches() for t in as_bytes(batch)]


def count_chunk(docs: pa.Table, targets: pa.Table, buckets: int) -> pa.Table:
    """A row for every bucket in which the chunk has an entry; BEGIN is an entry of every chunk."""
    types = pa_schema(_COUNTS)
    if not docs.num_rows:
        return types.empty_table()
    own, codec = Chunk(texts_of(docs)), zstd()
    chosen = set(targets.column("doc_id").to_pylist())
    columns = [own.key, own.check, own.is_word, *own.counts(np.array([i is not None and i in chosen for i in docs.column("doc_id").to_pylist()], dtype=bool))]
    at = own.bucket_starts(buckets)
    used = np.flatnonzero(np.diff(at))
    data = [packed([c[at[i] : at[i + 1]] for c in columns], _ENTRY, codec) for i in used]
    chunk = np.full(len(used), docs.column("chunk")[0].as_py(), dtype=np.int64)
    return pa.Table.from_arrays([pa.array(chunk), pa.array(used), pa.array(np.diff(at)[used]), pa.array(data, pa.binary())], schema=types)


def entries(rows: pa.Table) -> tuple[np.ndarray, ...]:
    """The entries of a bucket's rows, one after the other: key, check, whether a word, counts (target, all)."""
    codec = zstd()
    parts = [unpacked(d.as_buffer(), n, _ENTRY, codec) for d, n in zip(rows.column("counts"), rows.column("n").to_pylist(), strict=True)]
    return tuple(np.concatenate(c) for c in zip(*parts, strict=True))


def first_of_each(key: np.ndarray, check: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order by key, and the places in it where a new key begins."""
    order = np.lexsort((check, key))
    return order, np.flatnonzero(np.concatenate(([True], (np.diff(key[order]) != 0) | (np.diff(check[order]) != 0))))


def add_bucket(rows: pa.Table) -> pa.Table:
    """Totals of a bucket's entries for each of its chunks."""
    lengths = rows.column("n").to_numpy()
    key, check, _, target, every = entries(rows)
    order, new = first_of_each(key, check)
    sums = np.zeros((2, len(key)), dtype=np.int64)
    for i, c in enumerate((target, every)):
        sums[i, order] = np.repeat(np.add.reduceat(c[order].astype(np.int64), new), np.diff(np.append(new, len(key))))
    ends, codec = np.cumsum(lengths), zstd()
    data = [packed([s[j - n : j] for s in sums], _TOTAL, codec) for n, j in zip(lengths, ends, strict=True)]
    return pa.Table.from_arrays([*(rows.column(c).combine_chunks() for c in ("chunk", "bucket", "n")), pa.array(data, pa.binary())], schema=pa_schema(_TOTALS))


def bucket_sizes(rows: pa.Table) -> pa.Table:
    """Target tokens, all tokens and different words among a bucket's entries."""
    key, check, is_word, target, every = entries(rows)
    words = is_word > 0
    different = len(first_of_each(key[words], check[words])[1]) if words.any() else 0
    sizes = (int(target[words].sum(dtype=np.int64)), int(every[words].sum(dtype=np.int64)), different)
    return pa.Table.from_arrays([pa.array([x]) for x in sizes], schema=pa_schema(_SIZES))


def score_chunk(docs: pa.Table, totals: pa.Table) -> pa.Table:
    """Scores of a chunk's documents by the totals of its entries."""
    types = pa_schema(_SCORES)
    if not docs.num_rows:
        return types.empty_table()
    own, codec = Chunk(texts_of(docs)), zstd()
    totals = totals.sort_by("bucket")
    parts = [unpacked(d.as_buffer(), n, _TOTAL, codec) for d, n in zip(totals.column("totals"), totals.column("n").to_pylist(), strict=True)]
    sums = np.empty((2, len(own.order)))
    sums[:, own.order] = [np.concatenate(c) for c in zip(*parts, strict=True)]
    own_tokens, all_tokens, n_words = (totals.column(c)[0].as_py() for c in ("own_tokens", "all_tokens", "words"))
    # without target tokens both models are the background's
    models = ((sums[0], own_tokens, 1.0), (sums[1], all_tokens, own_tokens / all_tokens)) if own_tokens else ((sums[1], all_tokens, 1.0),) * 2
    losses, some = [], own.lengths > 0
    for counts, tokens, scale in models:
        words, pairs = counts[: own.n + 1] * scale, counts[own.n + 1 :] * scale
        single = (words + FLOOR) / (tokens * scale + FLOOR * n_words) if n_words else words
        means = np.zeros(docs.num_rows)
        if some.any():
            p = (pairs + STRENGTH * single[own.word]) / (words[own.before] + STRENGTH)
            means[some] = np.add.reduceat(-np.log(p)[own.at], own.starts) / own.lengths[some]
        losses.append(means)
    score = [round(x, 9) for x in (losses[0] - losses[1]).tolist()]
    return pa.Table.from_arrays([docs.column("doc_id").combine_chunks(), pa.array(own.lengths), *map(pa.array, losses), pa.array(score, pa.float64())], schema=types)


def score_documents(docs: DataFrame, targets: DataFrame, size: int | None = None, bits: int | None = None, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """doc_id, n_tokens, loss_target, loss_background, score. targets: the doc_ids of target documents. ``size`` or ``bits``: bounded models."""
    docs = only(docs, "doc_id", "text")
    bounded_batches(docs.sparkSession)
    if size is None and bits is None:
        return exact_scores(docs, targets, chunk_bytes)
    return bounded_scores(docs, targets, size or VOCABULARY, bits or BITS)


def exact_scores(docs: DataFrame, targets: DataFrame, chunk_bytes: int) -> DataFrame:
    n = max((docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // chunk_bytes + 1, docs.sparkSession.sparkContext.defaultParallelism)
    # all rows of a doc_id lie in one chunk, where its target is too; rows without one are spread by their texts
    docs = docs.select(F.pmod(F.xxhash64(F.coalesce("doc_id", F.xxhash64("text"))), F.lit(n)).alias("chunk"), "doc_id", "text")
    chosen = targets.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").distinct()
    chosen = chosen.select(F.pmod(F.xxhash64("doc_id"), F.lit(n)).alias("chunk"), "doc_id")

    def count(own: pa.Table, targets: pa.Table) -> pa.Table:
        return count_chunk(own, targets, n)

    # both uses of the chunks have the same plan, so that their exchange is made once
    counts = docs.groupBy("chunk").cogroup(chosen.groupBy("chunk")).applyInArrow(count, _COUNTS)
    buckets = counts.groupBy("bucket")
    sizes = buckets.applyInArrow(bucket_sizes, _SIZES).agg(F.struct(F.sum("own_tokens").alias("own_tokens"), F.sum("all_tokens").alias("all_tokens"), F.sum("words").alias("words")).alias("s"))
    totals = buckets.applyInArrow(add_bucket, _TOTALS).withColumn("s", sizes.scalar()).select("chunk", "bucket", "n", "totals", "s.*")
    return docs.groupBy("chunk").cogroup(totals.groupBy("chunk")).applyInArrow(score_chunk, _SCORES)


def bounded_scores(docs: DataFrame, targets: DataFrame, size: int, bits: int) -> DataFrame:
    words = vocabulary(docs, size)
    chosen = targets.select(F.col("doc_id").cast("long").alias("doc_id")).distinct().withColumn("is_target", F.lit(True))
    # always by sorting, never by broadcast: targets grow with the corpus
    counts = counted(docs.join(chosen.hint("merge"), "doc_id", "left").select("text", F.coalesce("is_target", F.lit(False)).alias("is_target")), words, bits)
    n = len(words) + 1
    own, every = int(counts[0, :n].sum()), int(counts[1, :n].sum())
    background = Model(counts[1], n, own / every if own else 1.0)
    models = docs.sparkSession.sparkContext.broadcast((Model(counts[0], n, 1.0) if own else background, background))
    known = docs.sparkSession.sparkContext.broadcast({w: i + 1 for i, w in enumerate(words)})

    def make(batch: pa.RecordBatch) -> dict:
        out: dict = {"n_tokens": [], "loss_target": [], "loss_background": [], "score": []}
        for text in as_bytes(batch):
            ids = word_ids(text, known.value)
            at = cells(ids, bits) if len(ids) else ids
            a, b = (float(m.losses(ids, at).mean()) if len(ids) else 0.0 for m in models.value)
            for name, value in zip(out, (len(ids), a, b, round(a - b, 9)), strict=True):
                out[name].append(value)
        return {"doc_id": batch.column(0), **out}

    return per_batch(docs, make, _SCORES)
