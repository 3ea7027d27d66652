"""Near-duplicate groups by b-bit MinHash.

Every document gets ``HASHES`` minima over its distinct word shingles. Full minima make the band keys (candidate
generation); what is kept of each is only its low ``BITS`` bits, packed into longs. A candidate pair's similarity is
estimated from the number of equal fields, corrected for chance collisions; pairs that may reach the threshold are
confirmed on the full shingle sets.

Links are found without enumerating groups:
1. documents with the same shingle set form one class, which its smallest doc_id represents;
2. every class is compared with one leader per band and confirmed against the most similar, at most one pair per
   class; a second turn with other leaders looks across the trees that this gives;
3. bands that still hold classes of different trees are compared across trees only, and confirmed in full, so no
   link that would join two groups is lost;
4. components come from pointer jumping and min-label rounds over tables in the shared folder.

With 38 bands of 5 rows a pair at 0.8 similarity shares no band once in 3 million cases, at 0.85 once in 4 billion.

Cases: a null, empty or wordless text has no set, links with nothing and stays; a text of fewer words than the
shingle width is one shingle; rows that share a doc_id are one document in the graph (all their sets join it);
rows with a null doc_id link with nothing; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, blank_words, bounded_batches, enter, only, pa_schema, stored

BANDS, ROWS, BITS, HASHES = 38, 5, 2, 768
LONGS = HASHES * BITS // 64
#: Size of the filter that keeps texts without a pair in place.
SLOTS = 1 << 20
#: Standard deviations below the threshold at which an estimate still leads to a confirmation.
SLACK = 4.5
_SEEDS = np.random.Generator(np.random.PCG64(20231))
_MUL = (_SEEDS.integers(0, 2**32, HASHES, dtype=np.uint64) | np.uint64(1)).astype(np.uint32)
_ADD = _SEEDS.integers(0, 2**32, HASHES, dtype=np.uint64).astype(np.uint32)
_FOLD = _SEEDS.integers(0, 2**63, (BANDS, ROWS), dtype=np.uint64) | np.uint64(1)
_FIELDS = 0x5555555555555555


def shingle_set(text: bytes | None, width: int) -> np.ndarray:
    """The distinct hashes (64 bits) of the word shingles, sorted."""
    words = blank_words(text)
    if not words:
        return np.zeros(0, dtype=np.uint64)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))
    if len(words) <= width:
        width = len(words)
    n = len(h) - width + 1
    mixed = np.full(n, width, dtype=np.uint64)
    for i in range(width):
        mixed = (mixed ^ h[i : i + n]) * np.uint64(0x9E3779B97F4A7C15)
        mixed ^= mixed >> np.uint64(29)
    return np.unique(mixed)


def minima(shingles: np.ndarray) -> np.ndarray:
    """The minimum of each of the HASHES permutations of 32-bit values."""
    x = (shingles ^ (shingles >> np.uint64(32))).astype(np.uint32)
    low = np.full(HASHES, 0xFFFFFFFF, dtype=np.uint32)
    for i in range(0, len(x), 512):  # blocks that stay in the cache
        np.minimum(low, (x[None, i : i + 512] * _MUL[:, None] + _ADD[:, None]).min(axis=1), out=low)
    return low


def packed(low: np.ndarray) -> np.ndarray:
    """The low BITS bits of each (mixed) minimum, side by side in longs."""
    field = ((low * np.uint32(0x85EBCA6B)) ^ (low >> np.uint32(15))).astype(np.uint64) & np.uint64(2**BITS - 1)
    return (field.reshape(LONGS, -1) << (np.arange(64 // BITS, dtype=np.uint64) * np.uint64(BITS))).sum(axis=1, dtype=np.uint64).view(np.int64)


def band_keys(low: np.ndarray) -> np.ndarray:
    """One 64-bit key per band, from full minima."""
    rows = low[: BANDS * ROWS].astype(np.uint64).reshape(BANDS, ROWS) + np.uint64(1)
    key = (rows * _FOLD).sum(axis=1, dtype=np.uint64) + np.arange(BANDS, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return ((key ^ (key >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)).view(np.int64)


def signatures(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, n_shingles, s1, s2, bands, s00..): s1 and s2 are a 128-bit hash of the whole set, null without a set."""
    names = [f"s{i:02}" for i in range(LONGS)]
    schema = "doc_id bigint, n_shingles bigint, s1 bigint, s2 bigint, bands array<bigint>, " + ", ".join(f"{n} bigint" for n in names)
    types = pa_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("near")
        for batch in batches:
            n, sets, bands, packs = [], [], [], []
            for text in as_bytes(batch):
                shingles = shingle_set(text, width)
                n.append(len(shingles))
                if len(shingles):
                    low = minima(shingles)
                    sets.append(np.frombuffer(xxhash.xxh3_128_digest(shingles.tobytes()), dtype="<i8"))
                    bands.append(band_keys(low)), packs.append(packed(low))
                else:
                    sets.append(None), bands.append(None), packs.append(np.zeros(LONGS, dtype=np.int64))
            columns = [batch.column(0), n, [x if x is None else int(x[0]) for x in sets], [x if x is None else int(x[1]) for x in sets], bands]
            columns += [np.ascontiguousarray(c) for c in np.array(packs, dtype=np.int64).reshape(-1, LONGS).T]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=t.type) if not isinstance(c, pa.Array) else c for c, t in zip(columns, types, strict=True)], schema=types)

    return docs.mapInArrow(run, schema)


def similarity_estimate(a: str, b: str) -> Column:
    """Collision-corrected similarity of two packed signatures, from the columns of the aliases ``a`` and ``b``."""
    terms = []
    for i in range(LONGS):
        x = f"({a}.s{i:02} ^ {b}.s{i:02})"
        terms.append(f"bit_count(({x} | shiftrightunsigned({x}, 1)) & {_FIELDS}L)")
    differing = F.expr(" + ".join(terms))
    chance = 1 / 2**BITS
    return ((F.lit(1.0) - differing / F.lit(float(HASHES))) - F.lit(chance)) / F.lit(1 - chance)


def least_estimate(threshold: float) -> float:
    chance = 1 / 2**BITS
    p = threshold + (1 - threshold) * chance
    return threshold - SLACK * (p * (1 - p) / HASHES) ** 0.5 / (1 - chance)


def _slot(doc_id: Column) -> Column:
    return F.pmod(F.xxhash64(doc_id), F.lit(SLOTS)).cast("int")


def confirmed(pairs: DataFrame, docs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose full shingle sets reach ``percent``.

    Before texts move, a filter lets those go whose hash is none of the pairs': a table of at most SLOTS small numbers,
    whatever the corpus, so it may be broadcast; what it lets through beyond the pairs costs an exchange, no result.
    """
    pairs = stored(pairs, "pairs")
    slots = pairs.select(_slot(F.col("a")).alias("slot")).union(pairs.select(_slot(F.col("b")))).distinct()
    texts = docs.withColumn("slot", _slot(F.col("doc_id"))).join(F.broadcast(slots), "slot", "left_semi").select("doc_id", "text").dropDuplicates(["doc_id", "text"])
    both = (
        pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")
        .join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b")
        .select("a", "b", "text_a", "text_b")
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter("near")
        for batch in batches:
            keep, last, known = [], None, None
            for a, b in zip(as_bytes(batch, "text_a"), as_bytes(batch, "text_b"), strict=True):
                if b != last:
                    last, known = b, shingle_set(b, width)
                x = shingle_set(a, width)
                common = len(x) + len(known) - len(np.union1d(x, known))
                keep.append(100 * common >= percent * (len(x) + len(known) - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, type=pa.bool_()))

    return both.mapInArrow(run, "a bigint, b bigint")


def _jumped(parents: DataFrame, name: str) -> DataFrame:
    """(id, label): the root of every id of a forest (id, label = parent, smaller than id), by pointer jumping."""
    while True:
        up = parents.select(F.col("id").alias("label"), F.col("label").alias("up"))
        parents = stored(parents.join(up, "label", "left").select("id", F.coalesce("up", "label").alias("label"), F.col("up").isNotNull().alias("moved")), name)
        if not parents.filter("moved").take(1):
            return parents.select("id", "label")
        parents = parents.select("id", "label")


def components(edges: DataFrame) -> DataFrame:
    """(id, label) for every id of ``edges`` (a, b): the smallest id of its component. Rounds of least neighbours and jumps."""
    links = stored(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a < b").distinct(), "edges")
    ids: DataFrame | None = None
    while links.take(1):
        # every id points to its least neighbour if that is smaller: a forest; then links between roots remain
        forest = _jumped(links.groupBy(F.col("b").alias("id")).agg(F.min("a").alias("label")), "forest")
        moved = forest if ids is None else None
        if ids is None:
            ids = moved
        else:
            up = forest.select(F.col("id").alias("label"), F.col("label").alias("up"))
            ids = ids.join(up, "label", "left").select("id", F.coalesce("up", "label").alias("label"))
            ids = ids.unionByName(forest.join(ids, "id", "left_anti"))
        ids = stored(ids, "labels")
        root_a = forest.select(F.col("id").alias("a"), F.col("label").alias("ra"))
        root_b = forest.select(F.col("id").alias("b"), F.col("label").alias("rb"))
        links = links.join(root_a, "a", "left").join(root_b, "b", "left").select(F.coalesce("ra", "a").alias("x"), F.coalesce("rb", "b").alias("y"))
        links = stored(links.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).filter("a < b").distinct(), "edges")
    return ids if ids is not None else edges.sparkSession.createDataFrame([], "id bigint, label bigint")


def _low(band: Column) -> Column:
    return band.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int")


def near_groups(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept): one row per row of ``docs``."""
    docs = only(docs, "doc_id", "text")
    bounded_batches(docs.sparkSession)
    rows = stored(signatures(docs, width), "signatures")
    sets = rows.filter("s1 is not null and doc_id is not null").groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"))
    sets = stored(sets, "sets")
    # one row per class; a doc_id on several rows may stand for several sets
    keyed = rows.join(sets, ["s1", "s2"])
    reps = stored(keyed.filter("doc_id = rep").dropDuplicates(["doc_id", "s1", "s2"]).drop("rep"), "classes")
    same_doc = keyed.groupBy("doc_id").agg(F.min("rep").alias("a"), F.max("rep").alias("b")).filter("a <> doc_id or b <> a")

    sig = [f"s{i:02}" for i in range(LONGS)]
    low = F.lit(least_estimate(percent / 100))
    banded = reps.select(F.col("doc_id").alias("id"), F.explode("bands").alias("band"))
    crowded = banded.groupBy("band").agg(F.count("*").alias("n")).filter("n > 1").select("band")
    members = stored(banded.join(crowded, "band"), "members")
    packs = reps.select(F.col("doc_id").alias("id"), *sig)

    # every class and the most similar of the classes that lead its bands; other leaders in the second turn, across trees only
    links, trees = [], None
    for turn in range(2):
        there = members.withColumn("tree", F.col("id")) if trees is None else members.join(trees.select("id", F.col("label").alias("tree")), "id", "left").withColumn("tree", F.coalesce("tree", "id"))
        there = there.withColumn("turn_key", F.xxhash64("id", "band", F.lit(turn)))
        leaders = there.groupBy("band").agg(F.min(F.struct("turn_key", "id", "tree")).alias("m")).select("band", F.col("m.id").alias("head"), F.col("m.tree").alias("head_tree"))
        tries = there.join(leaders, "band").filter("tree <> head_tree").select("id", "head").distinct()
        scored = tries.join(packs.alias("l"), "id").join(packs.select(F.col("id").alias("head"), *sig).alias("r"), "head").select("id", "head", similarity_estimate("l", "r").alias("est")).filter(F.col("est") >= low)
        best = scored.groupBy("id").agg(F.max(F.struct("est", (-F.col("head")).alias("neg"))).alias("m")).select(F.col("id").alias("b"), (-F.col("m.neg")).alias("a"))
        links.append(stored(confirmed(best, docs, width, percent), "links"))
        trees = components(reduce(DataFrame.union, links))

    # what is left: across trees, in bands that hold several, every pair in the first band that it shares
    there = members.join(trees.select("id", F.col("label").alias("tree")), "id", "left").withColumn("tree", F.coalesce("tree", "id"))
    mixed = there.groupBy("band").agg(F.min("tree").alias("x"), F.max("tree").alias("y")).filter("x < y").select("band")
    short = F.transform("bands", _low)  # 31 bits are enough to tell two keys of the same band apart
    side = stored(there.join(mixed, "band").join(reps.select(F.col("doc_id").alias("id"), short.alias("short"), *sig), "id"), "mixed")
    l, r = side.alias("l"), side.alias("r")
    first_shared = F.get(F.filter(F.arrays_zip(F.col("l.short").alias("x"), F.col("r.short").alias("y")), lambda z: z["x"] == z["y"]), F.lit(0))["x"] == _low(F.col("l.band"))
    across = (
        l.join(r, (F.col("l.band") == F.col("r.band")) & (F.col("l.tree") != F.col("r.tree")) & (F.col("l.id") < F.col("r.id")) & (similarity_estimate("l", "r") >= low) & first_shared)
        .select(F.col("l.id").alias("a"), F.col("r.id").alias("b")).distinct()
    )
    second = stored(confirmed(across, docs, width, percent), "links")
    shared = same_doc.select("a", F.col("doc_id").alias("b")).union(same_doc.select(F.col("b").alias("a"), F.col("doc_id").alias("b"))).filter("a <> b")
    repeated = shared.join(rows.groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1").select(F.col("doc_id").alias("b")), "b", "left_semi")
    # between the trees there are few links: their components, then every id takes its tree's
    more = second.unionByName(repeated.select("a", "b"))
    up_a, up_b = trees.select(F.col("id").alias("a"), F.col("label").alias("ta")), trees.select(F.col("id").alias("b"), F.col("label").alias("tb"))
    more = more.join(up_a, "a", "left").join(up_b, "b", "left").select(F.coalesce("ta", "a").alias("a"), F.coalesce("tb", "b").alias("b"))
    top = components(more).select(F.col("id").alias("label"), F.col("label").alias("top"))
    joined = trees.join(top, "label", "left").select("id", F.coalesce("top", "label").alias("label"))
    labels = stored(joined.unionByName(top.select(F.col("label").alias("id"), F.col("top").alias("label")).join(trees, "id", "left_anti")), "labels")

    out = rows.join(sets, ["s1", "s2"], "left").select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("rep", "doc_id")).alias("rep"))
    out = out.join(labels.select(F.col("id").alias("rep"), "label"), "rep", "left")
    component = F.coalesce("label", "rep")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def one_per_group(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` whose document is kept, all columns; rows that share a kept doc_id all stay."""
    name = "gone"
    while name in {c.lower() for c in docs.columns}:
        name = "_" + name
    gone = near_groups(docs, width, percent).filter(~F.col("kept")).select(F.col("doc_id").alias(name)).distinct()
    return docs.join(gone, docs["doc_id"].cast("long") == gone[name], "left_anti")
