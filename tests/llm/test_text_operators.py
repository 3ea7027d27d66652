"""Brute-force versions of the corpus operators, on the smallest tables and on hand-made odd rows."""

import hashlib
import re
import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from semrank.llm import decontaminate, license_scan, line_dedup, media, near_dedup, token_files
from semrank.llm.common import alnum_words, blank_words, new_path, table
from semrank.llm.fm_index import FMIndex

ALNUM, BLANK = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", r"[^\x20\x09-\x0D]+"
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
LINE = "This line is long enough to count, İK."
ODD = [
    (1, None), (2, ""), (3, "\n\n"), (4, LINE), (5, f"  {LINE.upper()}\t\n{LINE}\nother"), (6, LINE + "\n" + "x" * 30), (7, "short"), (7, "short"),
    (8, "Ünïcode Straße K İ ½ ² 日本語 word " * 3), (9, "a\x0bb\x0cc\rd e f"), (10, "w " * 60_000), (11, "Licensed under CC BY-NC 4.0. cc by"), (12, "GNU General Public License, All rights reserved. all RIGHTS reserved"),
    (13, "one two three"), (14, "one two"), (15, "one two"), (16, " <|endoftext|> it's \n\n  \n x"),
]


def frame(spark, rows=ODD):
    """With columns whose names clash with those the operators make."""
    return spark.createDataFrame([(i, t, "en", "src1", "row", 5) for i, t in rows], "doc_id long, text string, lang string, source string, row string, pos int").repartition(3)


def all_docs(spark, sf_dir):
    own = [(r["doc_id"] + 1000, r["text"]) for r in table(spark, sf_dir, "documents").collect()]
    return own + ODD


def words(pattern, text):
    return re.findall(pattern, (text or "").translate(LOWER))


def test_word_kernels():
    for _, text in ODD:
        raw = None if text is None else text.encode()
        assert [w.decode() for w in alnum_words(raw)] == words(ALNUM, text)
        assert [w.decode() for w in blank_words(raw)] == words(BLANK, text)


def brute_lines(rows):
    strip = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(LOWER)
    holders = {}
    for i, text in rows:
        for line in (text or "").split("\n"):
            holders.setdefault(strip(line), set()).add(i)
    known = {k: max(v) for k, v in holders.items() if len(k) >= 20 and len(v) >= 3}
    out = []
    for i, text in rows:
        lines = (text or "").split("\n")
        kept = [x for x in lines if known.get(strip(x), i) == i]
        out.append((i, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return sorted(out)


def test_line_dedup(spark, sf_dir):
    rows = all_docs(spark, sf_dir)
    got = line_dedup.dedup_lines(frame(spark, rows))
    assert sorted((r["doc_id"], r["n_lines"], r["n_dropped"], hashlib.sha256(r["text"].encode()).hexdigest()) for r in got.collect()) == brute_lines(rows)
    assert line_dedup.dedup_lines(frame(spark).filter("false")).count() == 0
    assert line_dedup.dedup_lines(frame(spark, [(None, LINE), (None, LINE)])).agg(F.sum("n_dropped")).first()[0] == 0


def test_perfect_hash_is_minimal():
    keys = np.random.default_rng(1).integers(0, 2**63, 5000, dtype=np.uint64)
    keys = np.unique(keys)
    mph = line_dedup.PerfectHash.of(keys)
    assert sorted(mph.slots(keys).tolist()) == list(range(len(keys)))


def test_clashing_first_halves_of_hashes():
    import pandas as pd

    part = pd.DataFrame({"shard": [0] * 3, "h1": [5, 5, 9], "h2": [1, 2, 3], "n_docs": [3, 4, 5], "last": [7, 8, 9]})
    count, last = line_dedup._probe(np.array([5, 5, 9, 5, 77]), np.array([1, 2, 3, 9, 1]), line_dedup._build_shard(part).iloc[0])
    assert count.tolist() == [3, 4, 5, 0, 0] and last.tolist() == [7, 8, 9, 0, 0]


def test_fm_index_against_search():
    rng = np.random.default_rng(3)
    for top in (1, 2, 5, 40):
        text = rng.integers(0, top + 1, 400)
        index = FMIndex(text, top)
        phrases = np.full((60, 6), -1)
        lengths = rng.integers(1, 7, 60)
        for i, n in enumerate(lengths):
            a = rng.integers(0, 390)
            phrases[i, :n] = text[a : a + n] if i % 2 else rng.integers(1, top + 1, n)
        low, high = index.ranges(phrases, lengths)
        for i, n in enumerate(lengths):
            want = [a for a in range(400 - n + 1) if (text[a : a + n] == phrases[i, :n]).all() and (phrases[i, :n] > 0).all()]
            assert sorted(index.locate(np.arange(low[i], high[i])).tolist()) == want


def brute_leaks(rows, items, width=10, plain=False, ids=None):
    windows = {}
    for item, text in items:
        w = tuple(words(ALNUM, text))
        for i in range(max(1, len(w) - width + 1) if w else 0):
            windows.setdefault(w[i : i + width], set()).add(str(item))
    sizes = {len(k) for k in windows}
    out = []
    for i, text in rows:
        w, hit, found = words(ALNUM, text), set(), set()
        for n in sizes:
            for a in range(len(w) - n + 1):
                if own := windows.get(tuple(w[a : a + n])):
                    hit |= set(range(a, a + n))
                    found |= own
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()))
    return [(i, *r[1:]) for i, r in zip(ids, out, strict=True)] if plain else sorted(out)


def test_decontamination(spark, sf_dir):
    items = [(r["item_id"], r["text"]) for r in table(spark, sf_dir, "benchmark").collect()] + [(900, "one two"), (901, "ONE, two"), (902, None), (903, "..."), (904, "w " * 12)]
    rows = all_docs(spark, sf_dir) + [(20, "x " + items[0][1] + " y " + items[1][1])]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.find_leaks(frame(spark, rows).withColumn("n_hit", F.lit("own")), bench)
    assert sorted((r["doc_id"], r["n_words"], r["n_hit"], r["n_items"], decontaminate.digest(r["items"])) for r in got.collect()) == brute_leaks(rows, items)
    spans = [r for r in got.filter("doc_id = 20").collect()][0]
    cut = decontaminate.cut_spans(spans["text"], spans["starts"], spans["ends"])
    assert len(words(ALNUM, cut)) == spans["n_words"] - spans["n_hit"]
    assert decontaminate.find_leaks(frame(spark), bench.filter("false")).agg(F.sum("n_hit")).first()[0] == 0
    assert decontaminate.find_leaks(frame(spark).filter("false"), bench).count() == 0


def test_decontamination_in_several_blocks(spark, monkeypatch):
    monkeypatch.setattr(decontaminate, "BLOCK_BYTES", 10)
    items = [(1, "one two"), (2, "two three"), (3, "general public"), (None, "public license"), (4, None)]
    rows = [*ODD, (40, "x one two three y general public license one two"), (None, "one two"), (None, "one two")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.find_leaks(frame(spark, rows), bench)
    assert sorted(((r["doc_id"], r["n_words"], r["n_hit"], r["n_items"], decontaminate.digest(r["items"])) for r in got.collect()), key=repr) == sorted(brute_leaks([(str(i), t) for i, t in rows], [("null" if i is None else i, t) for i, t in items], plain=True, ids=[i for i, _ in rows]), key=repr)


def test_decontamination_keeps_clashing_columns_under_a_prefix(spark):
    docs = frame(spark, [(1, "one two three")]).withColumns({"n_words": F.lit("own"), "items": F.lit(7)})
    bench = spark.createDataFrame([(1, "one two")], "item_id long, text string")
    row = decontaminate.find_leaks(docs, bench, prefix="leak_").first()
    assert (row["n_words"], row["items"], row["leak_n_words"], row["leak_n_hit"], row["leak_items"]) == ("own", 7, 3, 2, ["1"])
    assert decontaminate.find_leaks(docs, bench).first()["n_words"] == 3


def test_windows_are_compact():
    """Some ten bytes of arrays for a byte of benchmark, apart from the vocabulary."""
    rng = np.random.default_rng(0)
    items = [(i, " ".join(f"word{x}" for x in rng.integers(0, 3000, 200)).encode()) for i in range(500)]
    w = decontaminate.Windows(items, 10)
    assert w.phrases.nbytes + w.owner.nbytes + w.first.nbytes + w.lengths.nbytes < 10 * sum(len(t) for _, t in items)


def brute_boxes(data, start=0, end=None):
    """Nested (type, body, children) by another walk: a plain recursive reading of sizes."""
    out, at, end = [], start, len(data) if end is None else end
    while at < end:
        size, kind = int.from_bytes(data[at : at + 4], "big"), data[at + 4 : at + 8]
        body = at + 8
        if size == 1:
            size, body = int.from_bytes(data[at + 8 : at + 16], "big"), at + 16
        nested = kind in (b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf")
        out.append((kind, data[body : at + size], brute_boxes(data, body, at + size) if nested else []))
        at += size
    return out


def brute_media(data):
    """Payload, duration, samples and sync ranges of a container of this writer, table by table."""
    def find(tree, *path):
        for kind, body, sub in tree:
            if kind == path[0]:
                return body if len(path) == 1 else find(sub, *path[1:])

    number = lambda raw, at, n=4: int.from_bytes(raw[at : at + n], "big")
    tree = brute_boxes(data)
    stbl = lambda kind: find(tree, b"moov", b"trak", b"mdia", b"minf", b"stbl", kind)
    mdhd = find(tree, b"moov", b"trak", b"mdia", b"mdhd")
    samples, offsets = number(stbl(b"stsz"), 8), [number(stbl(b"co64"), 8 + 8 * i, 8) for i in range(number(stbl(b"co64"), 4))]
    runs = [(number(stbl(b"stsc"), 8 + 12 * i), number(stbl(b"stsc"), 12 + 12 * i)) for i in range(number(stbl(b"stsc"), 4))]
    places = []
    for i, offset in enumerate(offsets, 1):
        places += [offset + j for j in range([n for first, n in runs if first <= i][-1])]
    sync = [number(stbl(b"stss"), 8 + 4 * i) for i in range(number(stbl(b"stss"), 4))]
    assert len(places) == samples
    return bytes(data[p] for p in places), number(mdhd, 16) * 1000 // number(mdhd, 12), samples, [places[k - 1] for k in sync]


def test_media(spark, sf_dir):
    rows = all_docs(spark, sf_dir)
    got = sorted((tuple(r) for r in media.media_round_trip(frame(spark, rows)).collect()), key=repr)
    want = []
    for i, t in rows:
        raw = (t or "").encode()
        full = raw + bytes(-len(raw) % 64 if raw else 64)
        data = media.encode(full)
        payload, ms, samples, keys = brute_media(data)
        assert payload == full and keys[0] == data.index(full, len(data) - len(full)) and len(keys) == -(-len(full) // 4096)
        feature = f"codec=raw;handler=soun;ms={ms};samples={samples};keyframes={len(keys)};ranges=" + ",".join(f"{k}+1" for k in keys)
        want.append((i, len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-64:]), len(data), hashlib.sha256(data).hexdigest(), feature, "raw", "soun", ms, samples, 1, [0] * len(keys), keys, [1] * len(keys), False))
    assert got == sorted(want, key=repr)
    assert media.media_round_trip(frame(spark).filter("false")).count() == 0


def test_media_of_broken_and_foreign_columns(spark):
    """Null, no container, tables that claim too much, offsets beyond the file, cut-off files: a defined row each, no crash."""
    good = media.encode(b"q" * 10_000)

    def with_count(kind, at, n, data=good):
        i = data.index(kind) + at
        return data[:i] + struct.pack(">I", n) + data[i + 4 :]

    sized = with_count(b"stsz", 8, 0)  # sizes of their own: the table claims 10,000 of them and holds none
    rows = [None, b"", b"no container at all", good[:200], good[: len(good) - 5_000], sized, *(with_count(k, 8, 4_000_000_000) for k in (b"co64", b"stsc", b"stss", b"stts")), with_count(b"co64", 12, 77_777), with_count(b"moov", -4, 2**32 - 1)]
    rows += [b"\0\0\0\x08moov" * 3, struct.pack(">I4s", 8 * 40, b"moov") + b"".join(struct.pack(">I4s", 8 * (39 - i), b"trak") for i in range(39))]
    got = media.media_features(spark.createDataFrame([(i, 0, None if d is None else bytearray(d), "own") for i, d in enumerate(rows)], "doc_id long, n_bytes long, media binary, codec string")).orderBy("doc_id").collect()
    for i in (0, 1, 2):
        r = got[i]
        assert (r["codec"], r["duration_ms"], r["keyframe_offsets"], r["payload_bytes"], r["broken"]) == ("none", None, [], 0, False)
    assert got[4]["broken"] and got[4]["codec"] == "raw" and len(got[4]["keyframe_offsets"]) == 2
    assert got[5]["broken"] and got[5]["n_samples"] == 0 and got[5]["payload_bytes"] == 0
    assert all(r["broken"] for r in got[6:11])
    rng = np.random.default_rng(1)
    for _ in range(300):  # any byte may be anything
        data = bytearray(good[:900])
        for at in rng.integers(0, len(data), 6):
            data[at] = rng.integers(0, 256)
        assert isinstance(media.describe(bytes(data)), str) and media.described(bytes(data))["n_tracks"] >= 0


def test_media_keeps_every_keyframe_range(spark):
    data = bytearray(media.encode(b"x" * 100))
    at = data.index(b"stss") - 4
    box = struct.pack(">I4sII", 16 + 24, b"stss", 0, 6) + struct.pack(">6I", 1, 20, 40, 60, 80, 100)
    for parent in (b"moov", b"trak", b"mdia", b"minf", b"stbl"):
        i = data.index(parent) - 4
        data[i : i + 4] = struct.pack(">I", struct.unpack_from(">I", data, i)[0] + len(box) - 20)
    data[at : at + 20] = box
    row = media.media_features(spark.createDataFrame([(1, 100, data)], "doc_id long, n_bytes long, media binary")).first()
    assert "keyframes=6;" in row["feature"] and row["keyframe_lengths"] == [1] * 6
    assert [a - row["keyframe_offsets"][0] for a in row["keyframe_offsets"]] == [0, 19, 39, 59, 79, 99]


def test_media_sync_samples():
    t = media.Track(chunk_runs=[(1, 2), (2, 3)], n_samples=5, sizes=(10, 20, 30, 40, 50), chunks=(100, 1000), sync=(1, 4))
    assert t.chunk_ranges() == [(100, 30, 2), (1000, 120, 3)]
    assert t.keyframes() == [(100, 10), (1030, 40)]
    assert media.describe(b"not a container") == "codec=none" and media.describe(None) == "codec=none"


def test_token_files(spark, sf_dir):
    import public_tokenizers
    from tokenizers import Tokenizer

    rows = sorted(all_docs(spark, sf_dir), key=lambda x: (x[0], x[1] or ""))
    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want, start = [], 0
    for i, t in rows:
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [2], dtype="<u4")
        want.append((i, start, len(ids), zlib.crc32(ids.tobytes())))
        start += len(ids)
    got = token_files.token_round_trip(frame(spark, rows))
    assert sorted(tuple(r) for r in got.collect()) == sorted(want)
    assert token_files.token_round_trip(frame(spark).filter("false")).count() == 0
    assert token_files.token_round_trip(frame(spark, [(None, "a"), (1, "b")])).orderBy("start").first()["doc_id"] is None


def test_one_document_of_a_shard(spark, tmp_path):
    import public_tokenizers

    path = f"file://{tmp_path}/shards"
    shards = token_files.write_shards(frame(spark), path, public_tokenizers.path("byte_bpe_50k.json"))
    where, _ = token_files.file_system(path)
    shard = token_files.Shard(where, shards[0][0])
    whole = list(shard.documents())
    assert shard.document(len(whole) - 1).tolist() == whole[-1][1].tolist()


def brute_near(rows, width, percent):
    def shingles(text):
        w = words(BLANK, text)
        return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()

    sets = [(i, shingles(t)) for i, t in rows]
    label = {i: i for i, _ in rows}

    def root(i):
        while label[i] != i:
            i = label[i]
        return i

    for x, (i, a) in enumerate(sets):
        for j, b in sets[:x]:
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                p, q = sorted((root(i), root(j)))
                label[q] = p
    return sorted((i, len(s), root(i), root(i) == i) for i, s in sets)


@pytest.mark.parametrize(("width", "percent"), [(3, 85), (5, 80)])
def test_near_groups(spark, sf_dir, width, percent):
    base = [f"w{i}" for i in range(120)]
    chain = [(200 + k, " ".join(base[: 120 - 2 * k] + [f"v{i}" for i in range(2 * k)])) for k in range(30)]
    rows = all_docs(spark, sf_dir) + chain + [(300, chain[3][1]), (100, chain[9][1])]
    got = near_dedup.near_groups(frame(spark, rows), width, percent)
    assert sorted(tuple(r) for r in got.collect()) == brute_near(rows, width, percent)
    assert near_dedup.near_groups(frame(spark).filter("false")).count() == 0
    assert near_dedup.near_groups(frame(spark, [(None, "a b c d"), (1, "a b c d")])).filter("kept").count() == 2
    kept = near_dedup.one_per_group(frame(spark, rows), width, percent)
    assert {r["doc_id"] for r in kept.collect()} == {r[0] for r in brute_near(rows, width, percent) if r[3]}


def brute_phrases(rows):
    out = []
    for i, text in rows:
        w, places, labels = words(ALNUM, text), [], set()
        for phrase, label in license_scan.PHRASES.items():
            p = phrase.split(" ")
            own = [a for a in range(len(w) - len(p) + 1) if w[a : a + len(p)] == p]
            places += own
            labels |= {label} if own else set()
        out.append((i, len(w), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels))))
    return sorted(out, key=repr)


def brute_scan(text):
    """labels and best score of a text: for every diagonal, the longest rising run of hits within the drift."""
    w, labels, best = words(ALNUM, text), set(), 0.0
    for _, label, base, size, drift, must, template in license_scan.template_rows():
        found = sorted((a, -p) for p in range(size - 1) for a in range(len(w) - 1) if w[a : a + 2] == template[p : p + 2])
        for d in sorted({a + p for a, p in found}):
            own = [(a, -p) for a, p in found if 0 <= a + p - d <= drift]
            longest = []
            for i, (a, p) in enumerate(own):
                longest.append(1 + max((longest[j] for j, (b, q) in enumerate(own[:i]) if b < a and q < p), default=0))
            n = max(longest)
            enough = n == size - 1 if base else n >= license_scan.COVER * (size - 1) - 1e-9
            if enough and set(must) <= {p for _, p in own}:
                labels.add(label)
                best = max(best, n / (size - 1))
    return ",".join(sorted(labels)), best


def licence_texts():
    rng = np.random.default_rng(4)
    by_label = {label: text for label, text, _ in license_scan.TEMPLATES}
    mit, bsl = by_label["mit-notice"].split(" "), by_label["bsl-1.0"].split(" ")
    filler = lambda n: [f"filler{i}" for i in rng.integers(0, 50, n)]
    out = [by_label[label] for label in by_label]
    out.append(" ".join(x for i in range(0, len(mit), 2) for x in [*mit[i : i + 2], "xx", "yy"]))  # pairs with words between them
    out.append(" ".join(x for i in range(0, len(mit), 8) for x in [*mit[i : i + 8], "xx"]))  # a word every eight
    shuffled = [mit[i : i + 2] for i in range(0, len(mit), 2)]
    rng.shuffle(shuffled)
    out.append(" ".join(x for pair in shuffled for x in pair))
    out.append(" ".join(mit[len(mit) // 2 :] + mit[: len(mit) // 2]))  # halves the wrong way round
    out += [" ".join(mit[:n]) for n in (10, 20, 23, 25)]
    out += [" ".join([*filler(40), *bsl[:n], *filler(m), *bsl[n:], *filler(5), *mit]) for n, m in ((10, 3), (20, 12), (30, 30))]
    out.append("either version 3 of the license " + by_label["gpl-2.0"].replace("version 2", "version 4"))
    out.append("of the software " * 60 + by_label["mit"] + " the software is" * 40)
    out.append(" ".join(mit + filler(3) + mit))
    for _ in range(15):  # damaged copies
        w = by_label[list(by_label)[rng.integers(0, len(by_label))]].split(" ")
        for at in rng.integers(0, len(w), rng.integers(0, 1 + len(w) // 6)):
            w[at] = str(rng.choice(["the", "software", "x", ""]))
        out.append(" ".join(w))
    return out


def test_license_labels_and_scores(spark):
    """Whole, interleaved, shuffled, partial, damaged and repeated copies, versions of one license."""
    rows = list(enumerate(licence_texts()))
    got = {r["doc_id"]: (r["labels"], r["score"]) for r in license_scan.scan(frame(spark, rows)).collect()}
    for i, text in rows:
        labels, best = brute_scan(text)
        assert got[i][0] == labels and abs(got[i][1] - best) < 1e-12, (i, text[:80], got[i], labels, best)
    whole = dict(enumerate(label for label, _, _ in license_scan.TEMPLATES))
    assert all(whole[i] in got[i][0].split(",") for i in whole)
    n = len(whole)
    assert got[n][0] == got[n + 2][0] == got[n + 3][0] == "" and got[n + 1][0] == "mit-notice"
    assert "gpl-3.0-or-later" not in got[list(whole.values()).index("gpl-2.0")][0]


def test_license_scan(spark, sf_dir):
    rows = all_docs(spark, sf_dir) + [(30, "x Permission is hereby granted, free of charge, to any person obtaining a copy of this great software and associated documentation files (the Software), to deal in the Software without restriction.")]
    got = license_scan.scan(frame(spark, rows))
    assert sorted(((r["doc_id"], r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) for r in got.collect()), key=repr) == brute_phrases(rows)
    assert sorted((r["doc_id"], r["labels"]) for r in got.collect() if len(r["labels"])) == sorted((i, brute_scan(t)[0]) for i, t in rows if brute_scan(t)[0])
    assert "mit-notice" in got.filter("doc_id = 30").first()["labels"]
    assert license_scan.scan(frame(spark).filter("false")).count() == 0


@pytest.mark.parametrize("n", [5, 2000])
def test_short_documents_get_a_dictionary(spark, n):
    """Far below 256 ids a document, and even of few documents."""
    import public_tokenizers
    from pyarrow import fs

    rows = [(i, f"short note {i % 97} about thing {i % 13}") for i in range(n)]
    path = new_path(spark, "short")
    shards = token_files.write_shards(frame(spark, rows), path, public_tokenizers.path("byte_bpe_50k.json"))
    where, root = token_files.file_system(path)
    names = [f for f in where.get_file_info(fs.FileSelector(root)) if f.path.endswith(".zdict")]
    assert len(names) == 1 and names[0].size > 0 and sum(docs for _, docs, _ in shards) == n
    got = token_files.token_round_trip(frame(spark, rows))
    assert got.count() == n


def test_other_tokenizers_encode_whole_texts(spark):
    """Every tokenizer file that there is: the ids are the library's, whichever way it splits."""
    import glob
    import os

    import public_tokenizers
    from tokenizers import Tokenizer

    folder = os.path.dirname(public_tokenizers.path("byte_bpe_50k.json"))
    for path in sorted(glob.glob(f"{folder}/*.json")):
        try:
            tok = Tokenizer.from_file(path)
        except Exception:  # another kind of file
            continue
        codec = token_files.Codec(path, 2)
        texts = [t for _, t in ODD if t is None or len(t) < 10_000] + ["Hello  world's\n\n end ", " leading", "ÀÉ ñ 日本", "a\u00a0b"]
        want = [np.array(tok.encode(t or "", add_special_tokens=False).ids + [2]) for t in texts]
        got = [np.frombuffer(x, dtype=f"<u{codec.width}") for x in codec.encode(texts)]
        assert all((a == b).all() and len(a) == len(b) for a, b in zip(got, want, strict=True)), path
    assert token_files.known_split(public_tokenizers.path("byte_bpe_50k.json"))
