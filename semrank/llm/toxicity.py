"""A toxicity classifier with a counterfactual regulariser.

Logistic regression over the presence of words and word beginnings. Besides fitting the labels it penalises the
squared change of the score when identity terms in a labelled text are swapped for those of another group; a text
without identity terms is paired with two copies that mention one group each. So a neutral mention of a group
earns no score of its own, and swapped texts score alike.

The labelled rows are a bounded sample: of each class the ``PER_CLASS`` rows with the smallest hash of doc_id, and of
these as many, in order of the hash, as have ``SAMPLE_BYTES`` of text between them (the first one in any case).
Features are chosen by how much more often toxic texts of the sample have them. Every document is scored, whole.

Cases: a null, empty or wordless text scores as a text without any known feature; no labelled rows of either class
give every text the same score, the share of toxic rows (0 without labels); labels of unknown documents, null labels
and labels other than 0 and 1 are ignored; a doc_id labelled both ways counts once with each; of rows that share a doc_id the
smallest text is learnt from; rows are scored one by one; ``with_scores`` replaces a column that has the score's name.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import alnum_words, as_bytes, bounded_batches, enter, only, per_batch

#: Labelled rows of each class that are learnt from, bytes of their texts, features kept, and the score from which a text is toxic.
PER_CLASS, SAMPLE_BYTES, FEATURES, THRESHOLD = 2_500, 64 << 20, 4_096, 0.3
#: Names of groups of people, one tuple per kind; a term is swapped within its kind.
IDENTITY = (
    ("women", "men", "girls", "boys", "frauen", "männer", "femmes", "hommes", "mujeres", "hombres"),
    ("gay", "lesbian", "straight", "bisexual", "transgender", "queer"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist", "catholic", "protestant"),
    ("black", "white", "asian", "latino", "african", "european", "arab", "indigenous"),
    ("immigrant", "refugee", "foreigner", "citizen", "native", "tourist"),
    ("blind", "deaf", "disabled", "elderly", "young", "autistic"),
)
_GROUP = {w.encode(): [x.encode() for x in kind if x != w] for kind in IDENTITY for w in kind}
_TERMS = sorted(_GROUP)
_MEMO = 200_000


def word_features(word: bytes) -> list[bytes]:
    """The word itself and its beginnings of four to six code points."""
    chars = word.decode("utf-8", "ignore")
    return [b"=" + word, *(b"^" + chars[:n].encode() for n in (4, 5, 6) if len(chars) > n)]


def swapped(words: set[bytes], salt: int) -> tuple[set[bytes], set[bytes]]:
    """Two views of a text's identity terms: its own and others of the same kinds; for a text without any, one mention against another or none."""
    own = set(words)
    if own:
        return own, {_GROUP[w][salt % len(_GROUP[w])] for w in own}
    a = _TERMS[salt % len(_TERMS)]
    return {a}, ({_GROUP[a][salt // 7 % len(_GROUP[a])]} if salt % 2 else set())


@dataclass
class Classifier:
    bias: float = -30.0
    weights: dict[bytes, float] = field(default_factory=dict)
    constant: float | None = 0.0

    def __getstate__(self):
        return self.bias, self.weights, self.constant

    def __setstate__(self, state):
        self.bias, self.weights, self.constant = state

    def scores(self, texts: Iterable[bytes | None]) -> list[float]:
        if self.constant is not None:
            return [self.constant for _ in texts]
        weights, memo = self.weights, _memo_of(self)
        out = []
        for text in texts:
            found: set[bytes] = set()
            if len(memo) > _MEMO:
                memo.clear()
            for word in set(alnum_words(text)):
                own = memo.get(word)
                if own is None:
                    own = memo[word] = tuple(f for f in word_features(word) if f in weights)
                if own:
                    found.update(own)
            z = self.bias + sum(weights[f] for f in sorted(found))
            out.append(round(1 / (1 + float(np.exp(-max(-50.0, min(50.0, z))))), 9))
        return out


_memos: dict[int, dict] = {}


def _memo_of(model: Classifier) -> dict:
    """Words already looked up by this worker, for the model that it now holds."""
    key = hash((model.bias, len(model.weights)))
    if key not in _memos:
        _memos.clear()
        _memos[key] = {}
    return _memos[key]


def _forget() -> None:
    _memos.clear()


def fit(texts: list[bytes | None], labels: list[int], counterfactual: float = 1.0, decay: float = 1e-5, steps: int = 400) -> Classifier:
    """counterfactual: weight of the penalty on score changes under swapped identity terms."""
    y = np.array(labels, dtype=np.float64)
    n_toxic, n = int(y.sum()), len(y)
    if not n_toxic or n_toxic == n:
        return Classifier(constant=float(n_toxic / n) if n else 0.0)
    # how many toxic and clean texts have each feature; sets of words are made again when needed, not kept
    toxic: Counter = Counter()
    for text, label in zip(texts, labels, strict=True):
        if label:
            toxic.update({f for w in set(alnum_words(text)) for f in word_features(w)})
    least = 2 if n_toxic < 200 else 3
    toxic = Counter({f: b for f, b in toxic.items() if b >= least})
    clean: Counter = Counter()
    for text, label in zip(texts, labels, strict=True):
        if not label:
            clean.update({f for w in set(alnum_words(text)) for f in word_features(w) if f in toxic})
    lift = {f: (b / n_toxic) / ((clean[f] + 0.5) / (n - n_toxic)) for f, b in toxic.items()}
    chosen = sorted((f for f, v in lift.items() if v >= 3), key=lambda f: (-toxic[f] * np.log(lift[f]), f))[:FEATURES]
    chosen += sorted({f for w in _TERMS for f in word_features(w)} - set(chosen))
    place = {f: i for i, f in enumerate(chosen)}

    def places(words: Iterable[bytes]) -> set[int]:
        return {place[f] for w in words for f in word_features(w) if f in place}

    def rows(views: list[set[int]]) -> tuple[np.ndarray, np.ndarray]:
        return np.repeat(np.arange(len(views)), [len(v) for v in views]), np.array([p for v in views for p in sorted(v)], dtype=np.int64)

    own, left, right = [], [], []
    for i, text in enumerate(texts):
        words = set(alnum_words(text))
        terms = words & _GROUP.keys()
        rest = places(words - terms)
        a, b = swapped(terms, i)
        own.append(rest | places(terms)), left.append(rest | places(a)), right.append(rest | places(b))
    (r, c), (ra, ca), (rb, cb) = rows(own), rows(left), rows(right)
    share = np.where(y == 1, n / (2 * n_toxic), n / (2 * (n - n_toxic)))
    w, bias = np.zeros(len(chosen)), 0.0
    m, v = np.zeros(len(chosen) + 1), np.zeros(len(chosen) + 1)
    for step in range(1, steps + 1):
        z = bias + np.bincount(r, w[c], n)
        gap = share * (1 / (1 + np.exp(-np.clip(z, -50, 50))) - y) / n
        change = 2 * counterfactual / n * (np.bincount(ra, w[ca], n) - np.bincount(rb, w[cb], n))
        g = np.bincount(c, gap[r], len(w)) + np.bincount(ca, change[ra], len(w)) - np.bincount(cb, change[rb], len(w)) + decay * w
        g = np.append(g, gap.sum())
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        w, bias = w - move[:-1], bias - move[-1]
    # the classes weighed alike while fitting; a text that looks as much like either gets the score of THRESHOLD
    bias += float(np.log(THRESHOLD / (1 - THRESHOLD)))
    return Classifier(round(float(bias), 9), {f: round(float(w[i]), 9) for f, i in place.items() if abs(w[i]) > 1e-6}, None)


def held_out(doc_id):
    """Whether a row is kept from learning: crc32 of the doc_id as text, modulo 4, is 2."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, per_class: int = PER_CLASS, counterfactual: float = 1.0, sample_bytes: int = SAMPLE_BYTES) -> Classifier:
    rows = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).filter("toxic in (0, 1) and doc_id is not null").filter(~held_out("doc_id")).distinct()
    picks = [rows.filter(F.col("toxic") == t).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for t in (0, 1)]
    sample = picks[0].union(picks[1])
    texts = only(docs, "doc_id", "text").join(F.broadcast(sample), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))
    own, size = [], 0
    for r in texts.orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").toLocalIterator():
        raw = None if r["text"] is None else r["text"].encode()
        size += len(raw or b"")
        if own and size > sample_bytes:
            break
        own.append((r["doc_id"], r["toxic"], raw))
    own.sort(key=lambda x: x[:2])
    return fit([x[2] for x in own], [x[1] for x in own], counterfactual)


def with_scores(docs: DataFrame, model: Classifier, name: str = "toxic_score") -> DataFrame:
    """All columns of ``docs`` and the score, named ``name``."""
    bounded_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop(name)

    def run(batches):
        enter("toxicity", _forget)
        for batch in batches:
            scores = pa.array(shared.value.scores(as_bytes(batch)), type=pa.float64())
            yield pa.RecordBatch.from_arrays([*batch.columns, scores], names=[*batch.schema.names, name])

    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(name, T.DoubleType())]))


def score_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted: one row per row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(learn(docs, labels))

    def make(batch: pa.RecordBatch) -> dict:
        enter("toxicity", _forget)
        return {"doc_id": batch.column(0), "score": shared.value.scores(as_bytes(batch))}

    scored = per_batch(only(docs, "doc_id", "text"), make, "doc_id bigint, score double")
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
