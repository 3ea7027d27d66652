"""Rankers: anything that orders a short list of documents in one call.

All are picklable and are created once per Python worker. ``rank`` gets a batch of requests and returns, for each,
the positions of its documents (from 0), best first.
"""

from __future__ import annotations

import hashlib
import json
import math
import re
import sys
import time
import urllib.request
from dataclasses import dataclass, field, replace
from functools import lru_cache

import numpy as np

_TOKEN = re.compile(r"[a-z]+")
#: A response that is a number: decimal digits, no names such as nan or inf.
_NUMBER = re.compile(r"[+-]?(?:[0-9]+\.?[0-9]*|\.[0-9]+)(?:[eE][+-]?[0-9]{1,2})?")


@dataclass
class ListRequest:
    """One call: documents with what rankers may look at. ``pivots``: the first so many are pivots in settled order."""

    call_id: str
    ids: list[int]
    payloads: list[str | None]
    scores: list[float | None]
    query: str = ""
    pivots: int = 0


@dataclass
class Lists:
    """Many calls of rankers that read the score column: a name and a size each, and their documents one after the other."""

    names: list[str]
    sizes: np.ndarray
    ids: list[bytes]
    scores: np.ndarray
    slots: np.ndarray


def unit_hash(*parts) -> float:
    """A number in (0, 1) that depends on the parts only."""
    raw = hashlib.blake2b(":".join(map(str, parts)).encode(), digest_size=8).digest()
    return (int.from_bytes(raw, "little") + 0.5) / 2**64


def unit_hashes(seed, names: list[str], sizes: list[int], ids: list[bytes]) -> np.ndarray:
    """``unit_hash(seed, name, id)`` of every document of many lists; without the name where that is empty."""
    out, at, new = [], 0, hashlib.blake2b
    for name, size in zip(names, sizes, strict=True):
        begin, own = (f"{seed}:{name}:" if name else f"{seed}:").encode(), ids[at : at + size]
        at += size
        if size > 3:
            begun = new(begin, digest_size=8).copy
            for i in own:
                h = begun()
                h.update(i)
                out.append(h.digest())
        else:
            out += [new(begin + i, digest_size=8).digest() for i in own]
    return (np.frombuffer(b"".join(out), "<u8") + 0.5) / 2**64


@lru_cache(maxsize=2048)
def tokens(text: str | None) -> frozenset[str]:
    """Distinct words; those of the last texts are kept, since a text is in many lists."""
    return frozenset(map(sys.intern, _TOKEN.findall((text or "").lower())))


class Ranker:
    """Orders by ``score`` descending, then id. Subclasses say what a document's score is."""

    #: Whether the score is a column, so that the kernel can stay in the JVM.
    native = False

    def score(self, request: ListRequest, i: int) -> float:
        raise NotImplementedError

    def rank(self, requests: list[ListRequest]) -> list[list[int]]:
        out = []
        for r in requests:
            s = [self.score(r, i) for i in range(len(r.ids))]
            out.append(sorted(range(len(r.ids)), key=lambda i: (-s[i], r.ids[i])))
        return out


class ColumnRanker(Ranker):
    """A perfect ranker whose truth is the score column."""

    native = True

    def score(self, request, i):
        s = request.scores[i]
        return -math.inf if s is None else s


@dataclass
class LexicalRanker(Ranker):
    """Relevance as the number of distinct query tokens that the document holds. Without a query of its own it takes the request's."""

    query: str | None = None

    def rank(self, requests):
        out = []
        for r in requests:
            q = tokens(self.query if self.query is not None else r.query)
            s = [len(q & tokens(p)) for p in r.payloads]
            out.append(sorted(range(len(r.ids)), key=lambda i: (-s[i], r.ids[i])))
        return out


@dataclass
class VectorRanker(Ranker):
    """Cosine with a query vector; payloads are JSON arrays of numbers."""

    vector: list[float]

    def score(self, request, i):
        v, q = np.array(json.loads(request.payloads[i])), np.array(self.vector)
        size = float(np.linalg.norm(v) * np.linalg.norm(q))
        return round(float(v @ q) / size, 6) if size else 0.0


@dataclass
class NoisyRanker(Ranker):
    """Another ranker's score with Gumbel noise that depends on call and document."""

    base: Ranker
    sigma: float
    seed: int = 0

    def score(self, request, i):
        noise = -math.log(-math.log(unit_hash(self.seed, request.call_id, request.ids[i])))
        return self.base.score(request, i) + self.sigma_of(request) * noise

    def sigma_of(self, request) -> float:
        return self.sigma

    def scored(self, lists: Lists) -> np.ndarray:
        """``score`` of every document of many lists, where the base is the score column."""
        return lists.scores + self.sigmas(lists.sizes) * -np.log(-np.log(unit_hashes(self.seed, lists.names, lists.sizes.tolist(), lists.ids)))

    def sigmas(self, sizes: np.ndarray):
        """``sigma_of`` for every document of lists of such sizes."""
        return self.sigma


@dataclass
class PairNoiseByListSize(NoisyRanker):
    """Noise that grows with the length of the list beyond a knee: long lists are ranked badly."""

    knee: int = 64

    def sigma_of(self, request):
        return self.sigma * (1 + max(0, len(request.ids) - self.knee) / 8)

    def sigmas(self, sizes):
        return np.repeat(self.sigma * (1 + np.maximum(0, sizes - self.knee) / 8), sizes)


@dataclass
class PositionBiasedRanker(NoisyRanker):
    """A general-purpose model used listwise: late slots lose, and noise is high."""

    beta: float = 1.0

    def score(self, request, i):
        return super().score(request, i) - self.beta * i

    def scored(self, lists):
        return super().scored(lists) - self.beta * lists.slots


@dataclass
class LexicalScore(Ranker):
    """The lexical score as a base for noisy rankers."""

    query: str | None = None

    def score(self, request, i):
        return float(len(tokens(self.query if self.query is not None else request.query) & tokens(request.payloads[i])))


@dataclass
class ContradictingRanker(Ranker):
    """Swaps two pivots of a response with some probability."""

    base: Ranker
    p: float
    seed: int = 0

    def rank(self, requests):
        out = self.base.rank(requests)
        for r, order in zip(requests, out, strict=True):
            if r.pivots > 1 and unit_hash(self.seed, r.call_id) < self.p:
                a, b = order.index(0), order.index(1)
                order[a], order[b] = order[b], order[a]
        return out


@dataclass
class ReversedRanker(Ranker):
    """Another ranker's order turned round: the least relevant first. Pivots come to it worst first, so they go to the other best first."""

    base: Ranker

    def rank(self, requests):
        asked = [replace(r, ids=r.ids[: r.pivots][::-1] + r.ids[r.pivots :], payloads=r.payloads[: r.pivots][::-1] + r.payloads[r.pivots :], scores=r.scores[: r.pivots][::-1] + r.scores[r.pivots :]) for r in requests]
        out = []
        for r, order in zip(requests, self.base.rank(asked), strict=True):
            out.append([r.pivots - 1 - p if p < r.pivots else p for p in reversed(order)])
        return out


@dataclass
class BrokenRanker(Ranker):
    """Drops, repeats and invents documents."""

    base: Ranker

    def rank(self, requests):
        return [[*o[: max(1, len(o) - 1)], o[0], len(o) + 7] for o in self.base.rank(requests)]


@dataclass
class PointScorer:
    """A pointwise model: a coarse number from 1 to ``top`` as text, sometimes no number at all."""

    base: Ranker
    top: int = 5
    invalid_rate: float = 0.0
    seed: int = 0

    def respond(self, request: ListRequest) -> str:
        if unit_hash(self.seed, "invalid", request.ids[0]) < self.invalid_rate:
            return "n/a"
        s = self.base.score(request, 0)
        return str(max(1, min(self.top, round(1 + (self.top - 1) * (1 - math.exp(-max(0.0, s) / 10)) * (0.5 + unit_hash(self.seed, request.ids[0]))))))

    def responses(self, ids: list[int], scores: list[float | None]) -> list[str]:
        """``respond`` for many documents, where the base is the score column."""
        names, n = [b"%d" % i for i in ids], [len(ids)]
        valid = unit_hashes(self.seed, ["invalid"], n, names) >= self.invalid_rate
        near = {s: 1 - math.exp(-max(0.0, s or 0.0) / 10) for s in set(scores)}
        raw = np.rint(1 + (self.top - 1) * np.array([near[s] for s in scores]) * (0.5 + unit_hashes(self.seed, [""], n, names)))
        return [str(int(x)) if ok else "n/a" for x, ok in zip(np.clip(raw, 1, self.top).tolist(), valid.tolist(), strict=True)]


def parse_score(text: str | None, top: float) -> tuple[float, bool]:
    """A response as a number; what isn't one becomes half of the largest score. Second: whether it was valid."""
    got = _NUMBER.fullmatch((text or "").strip())
    return (float(got[0]), True) if got else (top / 2, False)


@dataclass
class HttpRanker(Ranker):
    """A ranking service: POSTs a batch as JSON, tries again after a growing pause, and remembers its last answers.

    Settled pivots go first in the prompt, which says that their order is known. Texts go out whole; ``max_chars`` clips
    them for a service that can't take long ones. Answers are known by model, query, ids and number of pivots.
    """

    url: str
    model: str
    timeout: float = 60.0
    retries: int = 3
    max_chars: int | None = None
    pause: float = 0.5
    remember: int = 10_000
    _known: dict = field(default_factory=dict, repr=False)

    def _post(self, body: bytes) -> dict:
        for attempt in range(self.retries):
            try:
                with urllib.request.urlopen(urllib.request.Request(self.url, body, {"Content-Type": "application/json"}), timeout=self.timeout) as f:
                    return json.load(f)
            except OSError:
                if attempt + 1 == self.retries:
                    raise
                time.sleep(self.pause * 2**attempt)
        raise AssertionError

    def rank(self, requests):
        from .prompts import build_listwise_prompt, parse_ranking, repair_ranking

        key = lambda r: hashlib.sha256(json.dumps([self.model, r.query, r.ids, r.pivots]).encode()).hexdigest()
        now = {k: self._known[k] for r in requests if (k := key(r)) in self._known}
        todo = [r for r in requests if key(r) not in now]
        if todo:
            texts = [[(p or "")[: self.max_chars] for p in r.payloads] for r in todo]
            prompts = [build_listwise_prompt(r.query, t[r.pivots :], t[: r.pivots]) for r, t in zip(todo, texts, strict=True)]
            answers = self._post(json.dumps({"model": self.model, "prompts": prompts}).encode())["responses"]
            now |= {key(r): repair_ranking(parse_ranking(a), len(r.ids))[0] for r, a in zip(todo, answers, strict=True)}
        self._known |= now
        for old in list(self._known)[: max(0, len(self._known) - self.remember)]:
            del self._known[old]
        return [[p - 1 for p in now[key(r)]] for r in requests]


@dataclass
class CachingRanker(Ranker):
    """Another ranker's answers, replayed when a task runs again with the same lists."""

    base: Ranker
    known: dict = field(default_factory=dict)
    hits: int = 0

    def rank(self, requests):
        todo = [r for r in requests if (r.query, tuple(r.ids)) not in self.known]
        self.hits += len(requests) - len(todo)
        for r, o in zip(todo, self.base.rank(todo) if todo else [], strict=True):
            self.known[r.query, tuple(r.ids)] = o
        return [self.known[r.query, tuple(r.ids)] for r in requests]
