"""Classifier, language models, WARC archives, budgets and the pipeline."""

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from semrank.llm import lm_scoring, mixing, toxicity, warc
from semrank.llm.common import new_path, table


def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")


@pytest.fixture(scope="module")
def labelled(spark):
    rng = np.random.default_rng(5)
    plain = [f"word{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(600):
        w = list(rng.choice(plain, rng.integers(5, 60)))
        toxic = int(rng.random() < 0.2)
        if toxic:
            w.insert(rng.integers(0, len(w)), str(rng.choice(["grumblo", "snarkface", "snarkling"])))
        if rng.random() < (0.6 if toxic else 0.05):
            w.append("muslim")
        rows.append((i, " ".join(w), "en", "src1"))
        labels.append((i, 1, toxic))
    return docs(spark, rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int"), dict((i, t) for i, _, t in labels)


def test_toxicity_held_out_accuracy(spark, labelled):
    texts, labels, truth = labelled
    rows = toxicity.score_documents(texts, labels).collect()
    assert {r["doc_id"] for r in rows if r["held_out"]} == {i for i in truth if zlib.crc32(str(i).encode()) % 4 == 2}
    held = [r for r in rows if r["held_out"]]
    assert sum(r["predicted"] == truth[r["doc_id"]] for r in held) / len(held) > 0.97
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_counterfactual_penalty_lowers_the_weight_of_groups(labelled):
    texts, _, truth = labelled
    rows = texts.collect()
    data = [r["text"].encode() for r in rows], [truth[r["doc_id"]] for r in rows]
    plain, fair = toxicity.fit(*data, counterfactual=0.0), toxicity.fit(*data, counterfactual=1.0)
    neutral = b"word1 word2 muslim"
    assert fair.scores([neutral])[0] < plain.scores([neutral])[0]
    assert fair.scores([neutral])[0] < toxicity.THRESHOLD < fair.scores([b"word1 grumblo word2"])[0]


def test_toxicity_odd_rows(spark, labelled):
    texts, labels, _ = labelled
    odd = docs(spark, [(5000, None, None, None), (5001, "", "en", "x"), (5002, "z " * 100_000, "en", "x"), (None, "grumblo", "en", "x")])
    got = toxicity.score_documents(texts.union(odd), labels).filter("doc_id >= 5000 or doc_id is null").collect()
    assert len(got) == 4 and all(r["score"] is not None for r in got)
    assert toxicity.score_documents(texts, labels.filter("false")).agg(F.max("score")).first()[0] == 0.0
    assert toxicity.score_documents(texts, labels.filter("toxic = 1")).agg(F.min("score")).first()[0] == 1.0
    assert toxicity.score_documents(texts.filter("false"), labels).count() == 0


def brute_scores(model, rows):
    """Scores from the weights alone: words by a pattern, their beginnings, a sum and a logistic function."""
    out = []
    for i, text in rows:
        words = set(re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate({c: c + 32 for c in range(65, 91)})))
        found = {f for w in words for f in ("=" + w, *("^" + w[:n] for n in (4, 5, 6) if len(w) > n))}
        z = model.bias + sum(v for f, v in model.weights.items() if f.decode() in found)
        out.append((i, 1 / (1 + math.exp(-z))))
    return out


def test_toxicity_scores_against_the_weights(spark, sf_dir, labelled):
    texts, labels, _ = labelled
    rows = [(r["doc_id"], r["text"]) for r in texts.collect()] + [(r["doc_id"] + 10_000, r["text"]) for r in table(spark, sf_dir, "documents").collect()]
    rows += [(5000, None), (5001, ""), (5002, "GRUMBLO! Straße \u212a snarklings"), (5002, "grumblo"), (None, "muslim")]
    full = docs(spark, [(i, t, "en", "src1") for i, t in rows]).withColumns({"toxic_score": F.lit("own"), "score": F.lit(1)})
    model = toxicity.learn(full, labels)
    want = brute_scores(model, rows)
    got = toxicity.with_scores(full, model, "s").select("doc_id", "s", "toxic_score").collect()
    assert all(r["toxic_score"] == "own" for r in got)
    key = lambda x: (-1 if x[0] is None else x[0], x[1])
    for (i, a), (j, b) in zip(sorted(((r["doc_id"], r["s"]) for r in got), key=key), sorted(want, key=key), strict=True):
        assert i == j and abs(a - b) < 1e-8
    scored = toxicity.score_documents(full, labels)
    for (i, a), (j, b) in zip(sorted(((r["doc_id"], r["score"]) for r in scored.collect()), key=key), sorted(want, key=key), strict=True):
        assert i == j and abs(a - b) < 1e-8
    assert all(r["predicted"] == (r["score"] >= 0.3) for r in scored.collect())


def test_toxicity_sample_is_bounded(spark, labelled):
    """Rows that share a labelled doc_id, and a bound in bytes."""
    texts, labels, truth = labelled
    again = texts.union(texts.withColumn("text", F.concat("text", F.lit(" zzz")))).union(texts)
    assert toxicity.learn(again, labels).weights == toxicity.learn(texts, labels).weights
    few = toxicity.learn(texts, labels, sample_bytes=2_000)
    assert few.constant is not None or 0 < len(few.weights) < len(toxicity.learn(texts, labels).weights)


def brute_lm(rows, targets, size, bits):
    tokens = {i: (t or "").encode().lower().split() for i, t in rows}
    total = Counter(w for v in tokens.values() for w in v)
    known = {w: n + 1 for n, (w, _) in enumerate(sorted(total.items(), key=lambda x: (-x[1], x[0]))[:size])}
    single = {k: Counter() for k in "tb"}
    pair = {k: Counter() for k in "tb"}
    ids = {i: [known.get(w, 0) for w in v] for i, v in tokens.items()}
    cell = lambda v, w: int(lm_scoring.cells(np.array([v, w]), bits)[1])
    for i, own in ids.items():
        for k in "tb" if i in targets else "b":
            single[k].update(own)
            pair[k].update(cell(v, w) for v, w in zip([0, *own], own, strict=False))
    n = len(known) + 1
    scale = {"t": 1.0, "b": sum(single["t"].values()) / sum(single["b"].values())}
    out = {}
    for i, own in ids.items():
        loss = {}
        for k in "tb":
            one = lambda w, k=k: (single[k][w] * scale[k] + 0.5) / (sum(single[k].values()) * scale[k] + 0.5 * n)
            s = [-math.log(min(1, (pair[k][cell(v, w)] * scale[k] + 50 * one(w)) / (single[k][v] * scale[k] + 50))) for v, w in zip([0, *own], own, strict=False)]
            loss[k] = sum(s) / len(s) if s else 0.0
        out[i] = (len(own), loss["t"], loss["b"])
    return out


def test_lm_scores(spark, sf_dir):
    own = [(r["doc_id"], r["text"]) for r in table(spark, sf_dir, "documents").limit(60).collect()] + [(9001, None), (9002, "")]
    targets = {i for i, _ in own if i % 3 == 0}
    got = lm_scoring.score_documents(spark.createDataFrame(own, "doc_id long, text string"), spark.createDataFrame([(i,) for i in targets], "doc_id long"), size=500, bits=12)
    want = brute_lm(own, targets, 500, 12)
    for r in got.collect():
        n, t, b = want[r["doc_id"]]
        assert r["n_tokens"] == n and abs(r["loss_target"] - t) < 1e-4 and abs(r["loss_background"] - b) < 1e-4
    empty = spark.createDataFrame([], "doc_id long")
    assert lm_scoring.score_documents(spark.createDataFrame(own, "doc_id long, text string"), empty).agg(F.max(F.abs("score"))).first()[0] == 0.0
    assert lm_scoring.score_documents(spark.createDataFrame([], "doc_id long, text string"), empty).count() == 0


def brute_exact_lm(rows, targets):
    tokens = [(i, (t or "").encode().lower().split()) for i, t in rows]
    single, pair, out = {k: Counter() for k in "tb"}, {k: Counter() for k in "tb"}, []
    for i, own in tokens:
        for k in "tb" if i in targets else "b":
            single[k].update([None, *own] if own else [])
            pair[k].update(zip([None, *own], own, strict=False))
    n = len(set(single["b"]) - {None})
    total = {k: sum(single[k].values()) - single[k][None] for k in "tb"}
    scale = {"t": 1.0, "b": total["t"] / total["b"]}
    for i, own in tokens:
        loss = {}
        for k in "tb":
            one = lambda w, k=k: (single[k][w] * scale[k] + 0.5) / (total[k] * scale[k] + 0.5 * n)
            s = [-math.log((pair[k][v, w] * scale[k] + 50 * one(w)) / (single[k][v] * scale[k] + 50)) for v, w in zip([None, *own], own, strict=False)]
            loss[k] = sum(s) / len(s) if s else 0.0
        out.append((i, len(own), loss["t"], loss["b"]))
    return out


def test_lm_scores_of_every_word_and_bigram(spark, sf_dir):
    """Every word and bigram has its own count, in chunks of any size: more words than a bounded vocabulary holds."""
    own = [(r["doc_id"], r["text"]) for r in table(spark, sf_dir, "documents").limit(60).collect()]
    many = " ".join(f"rare{i}" for i in range(70_000))
    own += [(9001, None), (9002, " "), (own[0][0], own[1][1]), (None, "a text without id"), (None, None), (9003, many), (9004, "rare69999 rare7 rare69999"), (9006, "Rare1 rare2")]
    targets = {i for i, _ in own if i is not None and i % 3 == 0}
    frame, chosen = spark.createDataFrame(own, "doc_id long, text string"), spark.createDataFrame([(i,) for i in [*targets, None, 12345]], "doc_id long")
    want = sorted(brute_exact_lm(own, targets), key=str)
    for size in (8 << 20, 5_000):
        got = sorted(((r["doc_id"], r["n_tokens"], r["loss_target"], r["loss_background"], r["score"]) for r in lm_scoring.score_documents(frame, chosen, chunk_bytes=size).collect()), key=str)
        assert len(got) == len(want)
        for (i, n, t, b, score), (j, m, x, y) in zip(got, want, strict=True):
            assert (i, n) == (j, m) and abs(t - x) < 1e-9 and abs(b - y) < 1e-9 and abs(score - (x - y)) < 2e-9


PAGES = [(1, "http://a/1", "x" * 200), (2, "http://b/2", "x" * 200), (3, "http://a/3", None), (4, None, "short"), (5, "http://a/\r\n5", "short"), (6, "http://c", "é" * 60), (7, "http://c", "é" * 60), (8, "http://z", "big\r\n\r\n" * 200_000), (None, "http://n", "y" * 150)]


def test_warc_round_trip(spark):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string").repartition(3)
    got = {r["page_id"]: r for r in warc.round_trip(pages).collect()}
    first = {}
    for i, _, h in sorted(PAGES, key=lambda x: (x[0] is None, x[0])):
        raw = (h or "").encode()
        known = first.setdefault(raw, i) if len(raw) >= 100 else i
        r = got[i]
        assert (r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) == (len(raw), warc.payload_digest(raw), *(("response", None) if known == i else ("revisit", known)))
    assert len(got) == len(PAGES)
    assert warc.round_trip(pages.filter("false")).count() == 0


def test_warc_push_down_skips_payloads(spark):
    path = new_path(spark, "warc-test")
    warc.write_archives(spark.createDataFrame(PAGES, "page_id long, url string, html string"), path)
    read = warc.read_archives(spark, path)
    assert read.filter("record_type = 'revisit'").count() == 2
    plan = read.filter("record_type = 'revisit' and target_uri like 'http://b%'")._jdf.queryExecution().toString()
    assert read.filter("record_type = 'revisit' and target_uri like 'http://b%'").first()["page_id"] == 2
    assert read.filter("page_id in (4, 6)").count() == 2 and "semrank_warc" in plan
    lean = warc.read_archives(spark, path, ["page_id", "record_type", "content_length"])
    assert lean.columns == ["page_id", "record_type", "content_length"] and lean.filter("record_type = 'response'").agg(F.max("content_length")).first()[0] == 1_400_000


def opened(data):
    import pyarrow as pa

    return warc.Ranges(pa.BufferReader(data), len(data))


def test_warc_unwanted_payloads_stay_packed():
    """Bytes inflated for records that no rule admits, or of which no payload is asked for: headers only."""
    big = np.random.default_rng(2).integers(0, 256, 3_000_000, dtype=np.uint8).tobytes()
    data = b"".join(warc.encode_record(i, f"http://x/{i}", big, "d", None if i % 2 else 1) for i in range(1, 7))
    for rules, payloads, kept in ((warc.Rules(page_ids=frozenset({3})), True, 1), (warc.Rules(), False, 6)):
        before = warc._Member.inflated
        got = list(warc.records(opened(data), rules, payloads))
        used = warc._Member.inflated - before
        assert len(got) == kept and all((p == big) if payloads else p is None for _, _, p in got)
        assert used < (len(big) + 30_000 if payloads else 0) + 6 * 2_000
    assert [h["x-page-id"] for _, h, _ in warc.records(opened(data), warc.Rules(frozenset({"revisit"})), True)] == ["2", "4", "6"]


def test_warc_members_of_other_writers():
    """Without skip lengths; a number that isn't one; a cut-off file."""
    import gzip

    first = gzip.compress(b"WARC/1.0\r\nWARC-Type: response\r\nX-Page-ID: abc\r\nContent-Length: 70000\r\n\r\n" + b"y" * 70_000 + b"\r\n\r\n")
    data = first + warc.encode_record(5, None, b"z" * 10, "d", None)
    for payloads in (True, False):
        got = list(warc.records(opened(data), warc.Rules(), payloads))
        assert [(at, h["warc-type"], p if p is None else len(p)) for at, h, p in got] == [(0, "response", 70_000 if payloads else None), (len(first), "response", 10 if payloads else None)]
    assert [h["x-page-id"] for _, h, _ in warc.records(opened(data), warc.Rules(page_ids=frozenset({5})), False)] == ["5"]
    with pytest.raises(ValueError, match="cut off"):
        list(warc.records(opened(first[: len(first) // 2]), warc.Rules(), False))
    assert gzip.decompress(warc.gzip_member(b"abc" * 1000)) == b"abc" * 1000


def test_warc_repeated_page_ids_clashing_columns_and_rolled_files(spark):
    rows = [(1, "x" * 200), (1, "y" * 300), (2, "x" * 200), (3, "y" * 300), (3, "y" * 300), (1, "x" * 200), (4, "long " * 400_000)]
    pages = spark.createDataFrame([(i, "http://u", h, "own", 7, b"p") for i, h in rows], "page_id long, url string, html string, payload_digest string, refers_to int, payload binary").repartition(1)
    got = sorted(tuple(r) for r in warc.round_trip(pages).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect())
    digest = {h: warc.payload_digest(h.encode()) for _, h in rows}
    want = [(i, len(h), digest[h], "response" if i in (1, 4) else "revisit", None if i in (1, 4) else 1) for i, h in rows]
    assert sorted(want) == got
    path = new_path(spark, "warc-roll")
    warc.write_archives(pages, path, roll_bytes=1)
    assert warc.read_archives(spark, path).select("file").distinct().count() == len(rows)
    bare = warc.round_trip(pages.select("page_id", "html"))
    assert bare.count() == len(rows)


def fill(children, budget):
    """Budgets by repeated rounds: what a full child can't take is shared again."""
    out = dict.fromkeys(children, 0.0)
    live = {c for c, (cap, w) in children.items() if cap > 0 and w > 0}
    while live and budget > 1e-9:
        total = sum(children[c][1] for c in live)
        over = {c for c in live if out[c] + budget * children[c][1] / total >= children[c][0] - 1e-12}
        if not over:
            for c in live:
                out[c] += budget * children[c][1] / total
            return out
        for c in over:
            budget -= children[c][0] - out[c]
            out[c] = children[c][0]
        # restart the sharing of what is left among the others, from nothing
        budget += sum(out[c] for c in live - over)
        for c in live - over:
            out[c] = 0.0
        live -= over
    return out


def test_mixing_against_rounds(spark, sf_dir):
    rows = [(r["doc_id"], r["text"], r["lang"], r["source"]) for r in table(spark, sf_dir, "documents").collect()]
    rows += [(7001, "a b c", None, None), (7002, None, "en", "src1"), (7003, "d e f", "en", "other"), (7003, "d e f", "en", "other")]
    share = 0.7
    got = mixing.mixed(docs(spark, rows).withColumn("epochs", F.lit("own")), F.sum("tokens") * share, 2, 42, mixing.DOMAIN_WEIGHTS, mixing.LANG_WEIGHTS).collect()
    leaf = lambda s, lang: (f"d{int(s[3:]) % 4}" if s and s[-1].isdigit() else "dx", lang, s)
    tokens = Counter()
    for _, t, lang, s in rows:
        tokens[leaf(s, lang)] += len((t or "").split())
    tokens = {k: v for k, v in tokens.items() if v}
    caps = lambda depth, of: {p: sum(2 * v for k, v in tokens.items() if k[: depth + 1] == p) for p in {k[: depth + 1] for k in tokens if k[:depth] == of}}
    weights = [mixing.DOMAIN_WEIGHTS, mixing.LANG_WEIGHTS, {}]
    level = {(): share * sum(tokens.values())}
    for depth in range(3):
        level = {p: b for up, budget in level.items() for p, b in fill({p: (c, weights[depth].get(p[depth], 1.0)) for p, c in caps(depth, up).items()}, budget).items()}
    taken = Counter()
    for r in got:
        taken[r["domain"], r["lang"], r["source"]] += r["n_tokens"] * r["epochs"]
    longest = {k: max(len((t or "").split()) for _, t, lang, s in rows if leaf(s, lang) == k) for k in tokens}
    for k, b in level.items():
        assert -1 <= taken[k] - b <= 2 * longest[k] + 1, (k, b, taken[k])
    assert mixing.mixed(docs(spark, rows).filter("false"), F.sum("tokens")).count() == 0
    once = mixing.mixed_documents(docs(spark, rows), F.sum("tokens") * 0.5)
    assert once.columns == ["doc_id", "text", "lang", "source"] and 0 < once.count() < len(rows)


def brute_prefix(rows, share, seed, weights=({}, {}, {})):
    """With one epoch: in each leaf, the shortest prefix of the seeded order that reaches its budget."""
    leaf = lambda s, lang: (f"d{int(s[-2:] if s[-2:].isdigit() else s[-1]) % 4}" if s and s[-1].isdigit() else "dx", lang, s)
    md5 = lambda x: hashlib.md5(x.encode()).hexdigest()
    own = {}
    for i, t, lang, s in rows:
        if n := len((t or "").split()):
            own.setdefault(leaf(s, lang), []).append((md5(f"{seed}:{'null' if i is None else i}:{md5(t)}"), -1 if i is None else i, md5(t), n))
    caps = lambda depth, of: {p: sum(r[3] for k, v in own.items() for r in v if k[: depth + 1] == p) for p in {k[: depth + 1] for k in own if k[:depth] == of}}
    level = {(): share * sum(r[3] for v in own.values() for r in v)}
    for depth in range(3):
        level = {p: b for up, budget in level.items() for p, b in fill({p: (c, weights[depth].get(p[depth], 1.0)) for p, c in caps(depth, up).items()}, round(budget, 3)).items()}
    out = []
    for k, budget in level.items():
        at, budget = 0, round(budget, 3)
        for key in sorted({r[:3] for r in own[k]}):
            if at < budget - 1e-9:
                out += [key[1:]] * sum(r[:3] == key for r in own[k])
            at += sum(r[3] for r in own[k] if r[:3] == key)
    return sorted(out)


def test_mixing_of_long_numbers_null_ids_and_repeated_rows(spark):
    rng = np.random.default_rng(8)
    rows = [(int(i), " ".join(["w"] * int(n)), str(rng.choice(["en", "de"])), str(rng.choice(["src1", "src2", "s" + "9" * 40, "other"]))) for i, n in enumerate(rng.integers(1, 30, 200))]
    rows += [(None, f"text {i}", "en", "src1") for i in range(150)] + [(7, "the same row", "en", "src1")] * 80 + [(7, f"own text {i}", "en", "src1") for i in range(40)] + [(None, None, None, None), (None, "x", None, None)]
    frame = docs(spark, rows).withColumns({"epochs": F.lit("own"), "mix_whole": F.lit(3), "n_tokens": F.lit(1)})
    md5 = lambda x: hashlib.md5(x.encode()).hexdigest()
    for share in (0.1, 0.5, 0.93):
        once = mixing.mixed_documents(frame, F.sum("tokens") * share)
        assert once.columns == frame.columns
        assert sorted((-1 if r["doc_id"] is None else r["doc_id"], md5(r["text"])) for r in once.collect()) == brute_prefix(rows, share, 42)
    got = mixing.mixed(frame, F.sum("tokens") * 0.5, 1).collect()
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["row_hash"]) for r in got) == brute_prefix(rows, 0.5, 42)
    assert {r["domain"] for r in got if r["source"] and r["source"].startswith("s99")} == {"d3"}
    assert mixing.mixed_documents(frame.filter("false"), F.sum("tokens") * 0.5).count() == 0


def brute_pipeline(spark, rows, labels, items):
    """Each stage by itself on plain rows (doc_id, text, lang, source): what the pipeline must give, stage by stage."""
    from test_text_operators import brute_leaks, brute_near

    frame = docs(spark, rows)
    model = toxicity.learn(frame, labels)
    scores = brute_scores(model, [(r[0], r[1]) for r in rows]) if model.constant is None else [(r[0], model.constant) for r in rows]
    stages = [[r for r, (_, s) in zip(rows, scores, strict=True) if s < 0.3]]
    groups = {i: kept for i, _, _, kept in brute_near([(r[0], r[1]) for r in stages[-1]], 5, 80)}
    stages.append([r for r in stages[-1] if groups[r[0]]])
    hit = {i: n for i, _, n, *_ in brute_leaks([(r[0], r[1]) for r in stages[-1]], items)}
    stages.append([r for r in stages[-1] if not hit[r[0]]])
    taken = Counter(brute_prefix(stages[-1], corpus_pipeline.MIX_SHARE, corpus_pipeline.MIX_SEED, (mixing.DOMAIN_WEIGHTS, mixing.LANG_WEIGHTS, {})))
    stages.append([r for r in stages[-1] if r[1] and (r[0], hashlib.md5(r[1].encode()).hexdigest()) in taken])
    return stages


def test_pipeline_against_brute_force(spark, sf_dir):
    """Every stage of the whole run, and the ids of the last."""
    import public_tokenizers
    from tokenizers import Tokenizer

    own = table(spark, sf_dir, "documents")
    rows = [(r["doc_id"], r["text"], r["lang"], r["source"]) for r in own.collect()]
    items = [(r["item_id"], r["text"]) for r in table(spark, sf_dir, "benchmark").collect()]
    want = brute_pipeline(spark, rows, table(spark, sf_dir, "labels"), items)
    now = own
    for (name, stage), kept in zip(corpus_pipeline.STAGES[:4], want, strict=True):
        now = stage(spark, now, sf_dir)
        assert sorted(r["doc_id"] for r in now.collect()) == sorted(r[0] for r in kept), name
    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    ids, start = [], 0
    for i, text, _, _ in sorted(want[-1], key=lambda r: r[:2]):
        own_ids = np.array(tok.encode(text, add_special_tokens=False).ids + [2], dtype="<u4")
        ids.append((i, start, len(own_ids), zlib.crc32(own_ids.tobytes())))
        start += len(own_ids)
    got = corpus_pipeline.run(spark, sf_dir)
    assert got.columns == ["doc_id", "start", "n_tokens", "ids_crc32"]
    assert sorted(tuple(r) for r in got.collect()) == sorted(ids)


@pytest.fixture
def folder(spark, sf_dir):
    """Writes tables of its own as a data folder; those not given come empty."""

    def make(**tables):
        path = new_path(spark, "tables")
        for name in ("documents", "labels", "benchmark"):
            (tables[name] if name in tables else table(spark, sf_dir, name).limit(0)).write.parquet(f"{path}/{name}.parquet")
        return path

    return make


def test_pipeline_of_odd_tables(spark, sf_dir, folder):
    assert corpus_pipeline.run(spark, folder()).count() == 0
    odd = [(1, None, None, None), (2, "", "en", "src1"), (3, " \n ", "en", "src1"), (4, "one two three four five six", "en", "s" + "7" * 30), (4, "one two three four five six", "en", "s" + "7" * 30), (4, "another text of this id", "en", "src2"),
           (None, "no id here but words", None, None), (None, "no id here but words", None, None), (9, "w " * 200_000, "de", "src3"), (10, "w " * 200_000, "de", "src3")]
    clashing = {c: F.lit("own") for c in ("toxic_score", "gone", "n_words", "leak_n_hit", "items", "mix_epochs", "tokens", "b1", "n_tokens")}
    path = folder(documents=docs(spark, odd).withColumns(clashing))
    now = table(spark, path, "documents")
    for name, stage in corpus_pipeline.STAGES[:4]:
        now = stage(spark, now, path)
        assert now.columns == ["doc_id", "text", "lang", "source", *clashing], name
        assert all(r[c] == "own" for r in now.select(*clashing).distinct().collect() for c in clashing)
        n = now.count()
        assert n == (10 if name == "toxicity" else 9 if name in ("near_dedup", "decontaminate") else n), name
    done = corpus_pipeline.run(spark, path)
    # all that have words at 80 % of the tokens: whole prefixes of each leaf, null and repeated ids among them
    assert 0 < done.count() <= 6 and done.filter("n_tokens < 2").count() == 0


def test_pipeline(spark, sf_dir):
    stages = dict(corpus_pipeline.STAGES)
    own = table(spark, sf_dir, "documents")
    leak = table(spark, sf_dir, "benchmark").first()["text"]
    extra = spark.createDataFrame([(90_001, leak + " tail", "en", "src1", 5), (90_002, None, None, None, None)], own.schema)
    full = own.unionByName(extra)
    for name in ("toxicity", "near_dedup", "decontaminate", "mixing"):
        out = stages[name](spark, full, sf_dir)
        assert out.columns == own.columns, name
        assert 0 < out.count() <= full.count()
    assert stages["decontaminate"](spark, full, sf_dir).filter("doc_id = 90001").count() == 0
    done = corpus_pipeline.run(spark, sf_dir).collect()
    assert len(done) > 50 and sorted(r["start"] for r in done)[0] == 0
    assert all(r["n_tokens"] >= 1 for r in done)
