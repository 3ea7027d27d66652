"""The algorithms of ``engine`` over one scope held as arrays, for rankers whose scores are a column and noise.

All calls of a round are scored together, and all segments of a sort's level are dealt together. Calls, their names,
slots, ties and ledger are those of ``engine``, so where a scope is finished still says nothing about its result. Each
algorithm is a generator: it yields the ledger in batches and returns its result.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b, md5

import numpy as np
import pyarrow as pa

from ..schema import RankParams
from .rankers import ColumnRanker, Lists, NoisyRanker, PairNoiseByListSize, PositionBiasedRanker, Ranker

#: Documents that are scored at a time.
BATCH = 1 << 16
#: Bytes of shuffle keys that a worker remembers: scopes and runs often hold the same documents.
KEPT = 64 << 20
_keys: dict[tuple, np.ndarray] = {}
_TEXT, _LONG, _INT, _FLAG = pa.string(), pa.int64(), pa.int32(), pa.bool_()
#: Results (id is set) and calls, which ``topk.run_columns`` gives their run; none of these rankers' responses needs repair.
SCHEMA = pa.schema([("scope", _LONG), ("seg", _LONG), ("rank", _LONG), ("id", _LONG), ("algo", _TEXT), ("round", _INT), ("call_id", _TEXT), ("kind", _TEXT), ("n_items", _INT), ("n_pivots", _INT), ("chars_in", _LONG), ("contradiction", _FLAG)])


def columnar(ranker: Ranker) -> bool:
    """Whether a ranker's scores are the score column with noise of a known form."""
    return type(ranker) in (NoisyRanker, PairNoiseByListSize, PositionBiasedRanker) and type(ranker.base) is ColumnRanker


def ranges(sizes: np.ndarray) -> np.ndarray:
    """0, 1, ... for each size, one after the other."""
    return np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)


class Table:
    """Documents of a scope in order of id, named by their place in that order, and what calls need to know."""

    def __init__(self, ids: np.ndarray, scores: np.ndarray, proxies: np.ndarray, chars: np.ndarray, ranker: Ranker, params: RankParams, seed: int, scope: int) -> None:
        order = np.argsort(ids, kind="stable")
        order = order[np.append(ids[order][1:] != ids[order][:-1], True)]  # a repeated id counts once, its last row
        self.ids = ids[order]
        self.scores = np.where(np.isnan(scores[order]), -np.inf, scores[order])
        self.proxies = np.nan_to_num(proxies[order], nan=0.0, posinf=np.inf, neginf=-np.inf)
        self.chars = chars[order]
        self.names = [b"%d" % i for i in self.ids.tolist()]
        self.ranker, self.params, self.seed, self.scope = ranker, params, seed, scope
        self._print = blake2b(self.ids.tobytes()).digest()

    def __len__(self) -> int:
        return len(self.ids)

    def keys(self, turn: str, docs: np.ndarray, often: bool = False) -> np.ndarray:
        """The first 64 bits of ``kernel._place`` of documents; their order is that of ``kernel.shuffled``."""
        name = (self._print, self.seed, turn)
        if name in _keys:
            return _keys[name][docs]
        whole = often or 2 * len(docs) >= len(self)
        begin = f"{self.seed}:{turn}:".encode()
        own = self.names if whole else [self.names[i] for i in docs.tolist()]
        got = np.frombuffer(b"".join([md5(begin + x).digest() for x in own]), ">u8")[::2].astype(np.uint64)
        if not whole:
            return got
        for old in [x for x in _keys if x[0] != self._print] if sum(x.nbytes for x in _keys.values()) + got.nbytes > KEPT else []:
            del _keys[old]
        if sum(x.nbytes for x in _keys.values()) + got.nbytes <= KEPT:  # the first stay: runs go through the turns in order, again and again
            _keys[name] = got
        return got[docs]

    def shuffled(self, docs: np.ndarray, turn: str, seg: np.ndarray | None = None) -> np.ndarray:
        """Places of documents in the shuffle's order, segment by segment. docs are in order of segment (0, 1, ...) and id."""
        key = self.keys(turn, docs)
        bits = 0 if seg is None or not len(seg) else int(seg[-1]).bit_length()
        both = key if not bits else (seg.astype(np.uint64) << np.uint64(64 - bits)) | (key >> np.uint64(bits))
        order = np.argsort(both)
        if (both[order[1:]] == both[order[:-1]]).any():
            order = np.lexsort((key,) if seg is None else (key, seg))
        return order

    def ledger(self, phase: str, kind: str, turn: int, names: list[str], sizes: np.ndarray, pivots: int, chars: np.ndarray, contradicted: np.ndarray) -> pa.RecordBatch:
        n = len(names)
        same = lambda x, t: pa.repeat(pa.scalar(x, t), n)
        return pa.RecordBatch.from_arrays([
            same(self.scope, _LONG), pa.nulls(n, _LONG), pa.nulls(n, _LONG), pa.nulls(n, _LONG), same(phase, _TEXT), same(turn, _INT), pa.array(names, _TEXT),
            same(kind, _TEXT), pa.array(sizes, _INT), same(pivots, _INT), pa.array(chars, _LONG), pa.array(contradicted, _FLAG),
        ], schema=SCHEMA)

    def scored(self, names: list[str], docs: np.ndarray, sizes: np.ndarray, pivots: int) -> np.ndarray:
        """What the ranker gives each document of many lists, which lie one after the other, pivots first."""
        call = np.repeat(np.arange(len(sizes)), sizes)
        slot = ranges(sizes)
        if type(self.ranker) is PositionBiasedRanker and self.params.slot_order == "hash":
            rest = np.flatnonzero(slot >= pivots)
            order = np.lexsort((self.keys("slot0", docs[rest], True), call[rest]))
            placed = slot.copy()
            placed[rest[order]] = slot[rest]
            slot = placed
        return self.ranker.scored(Lists(names, sizes, [self.names[i] for i in docs.tolist()], self.scores[docs], slot))

    def ranked(self, docs: np.ndarray, sizes: np.ndarray, name, phase: str, kind: str, turn: int):
        """Many lists, best first. name(a, b): the names of calls a to b. Lists of one aren't calls."""
        ends, out = np.cumsum(sizes), []
        for a, b in _chunks(ends):
            own, n = docs[(ends[a - 1] if a else 0) : ends[b - 1]], sizes[a:b]
            names = name(a, b)
            s = self.scored(names, own, n, 0)
            call = np.repeat(np.arange(b - a), n)
            out.append(own[np.lexsort((own, -s, call))])
            many = n > 1
            if many.any():
                keep = names if many.all() else [x for x, m in zip(names, many.tolist(), strict=True) if m]
                yield self.ledger(phase, kind, turn, keep, n[many], 0, np.add.reduceat(self.chars[own], ends[a:b] - n - (ends[a - 1] if a else 0))[many], np.zeros(int(many.sum()), bool))
        return np.concatenate(out) if out else docs

    def dealt(self, rest: np.ndarray, sizes: np.ndarray, pivots: np.ndarray, segs: np.ndarray, number: int, phase: str, turn: int):
        """How many of its segment's pivots stand before each document. rest: documents in the order of the deal, ``sizes`` of each
        segment; pivots: a row for each segment, in settled order, the group of that number; segs: the segments' names."""
        m, room = pivots.shape[1], self.params.list_size - self.params.group
        lists = -(-sizes // room)
        seg = np.repeat(np.arange(len(sizes)), lists)
        at = ranges(lists)
        own = np.minimum(room, sizes[seg] - at * room)
        ends, out = np.cumsum(own), [np.zeros(0, np.int64)]
        for a, b in _chunks(ends + m * np.arange(1, len(ends) + 1)):
            docs, n = rest[(ends[a - 1] if a else 0) : ends[b - 1]], own[a:b]
            head = f"{self.scope}:{phase}:"
            tail = f":{turn}:bucket:{number}."
            names = [f"{head}{s}{tail}{j}" for s, j in zip(segs[seg[a:b]].tolist(), at[a:b].tolist(), strict=True)]
            slot = ranges(n + m)
            first = slot < m
            lead = pivots[seg[a:b]]
            both = np.empty(len(slot), np.int64)
            both[first], both[~first] = lead.ravel(), docs
            s = self.scored(names, both, n + m, m)
            call, best, mine = np.repeat(np.arange(b - a), n), s[first].reshape(-1, m), s[~first]
            before = np.zeros(len(docs), np.int64)
            for q in range(m):
                p, x = lead[:, q][call], best[:, q][call]
                before += (x > mine) | ((x == mine) & (p < docs))
            wrong = np.zeros(b - a, bool)
            for q in range(m - 1):
                wrong |= (best[:, q] < best[:, q + 1]) | ((best[:, q] == best[:, q + 1]) & (lead[:, q] > lead[:, q + 1]))
            out.append(before)
            starts = np.cumsum(n + m) - (n + m)
            yield self.ledger(phase, "bucket", turn, names, n + m, m, np.add.reduceat(self.chars[both], starts), wrong)
        return np.concatenate(out)


def _chunks(ends: np.ndarray) -> Iterator[tuple[int, int]]:
    """Lists a to b of about BATCH documents; ends: documents up to the end of each list."""
    a = 0
    while a < len(ends):
        b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + BATCH, "right")))
        yield a, b
        a = b


def _settled(t: Table, pivots: np.ndarray, segs: np.ndarray, phase: str, turn: int):
    """Each segment's pivots (a row, in order of id) in the order of one call."""
    count, p = pivots.shape
    if p < 2:
        return pivots
    name = lambda a, b: [f"{t.scope}:{phase}:{s}:{turn}:pivots:" for s in segs[a:b].tolist()]
    got = yield from t.ranked(pivots.ravel(), np.full(count, p), name, phase, "pivots", turn)
    return got.reshape(count, p)


def select(t: Table, k: int, turn: int = 0):
    """``engine.pivot_select``."""
    p, docs, left = t.params, np.arange(len(t)), min(k, len(t))
    zero, out = np.zeros(1, np.int64), [np.zeros(0, np.int64)]
    while left > 0:
        if left >= len(docs):
            out.append(docs)
            break
        if len(docs) <= p.list_size:
            name = f"{t.scope}:select:0:{turn}:base:"
            got = yield from t.ranked(docs, np.array([len(docs)]), lambda a, b, name=name: [name], "select", "base", turn)
            out.append(got[:left])
            break
        count = min(p.pivots, len(docs) - 1)
        if p.pivot_mode == "random":
            pivots = np.sort(docs[t.shuffled(docs, f"pivot{turn}")[:count]])
        else:
            start = max(0, min(left - 1, len(docs) - count))
            pivots = np.sort(docs[np.lexsort((docs, -t.proxies[docs]))[start : start + count]])
        ordered = (yield from _settled(t, pivots[None], zero, "select", turn))[0]
        rest = docs[~np.isin(docs, pivots)]
        rest = rest[t.shuffled(rest, f"deal{turn}")]
        bucket, used, asked = np.full(len(rest), -1), 0, np.arange(len(rest))
        if not p.early_stop:
            bucket[:] = 0
        for number, a in enumerate(range(0, count, p.group)):
            group = ordered[a : a + p.group]
            b = yield from t.dealt(rest[asked], np.array([len(asked)]), group[None], zero, number, "select", turn)
            if not p.early_stop:
                bucket += b
                used += len(group)
                continue
            found = b < len(group)
            bucket[asked[found]] = used + b[found]
            asked = asked[~found]
            used += len(group)
            if used < count and len(rest) - len(asked) + used >= left:
                break
        if p.early_stop:
            bucket[asked] = used
        shown, hidden = ordered[:used], ordered[used:]
        docs = zero[:0]
        for i in range(used + 1):
            own = rest[bucket == i]
            if i == used:
                own = np.append(own, hidden)
            if len(own) > left:
                docs = np.sort(own)
                break
            out.append(own)
            left -= len(own)
            if left and i < used:
                out.append(shown[i : i + 1])
                left -= 1
            if not left:
                break
        turn += 1
    return np.concatenate(out)


def sort(t: Table, turn: int = 0, seg: int = 0, phase: str = "sort"):
    """``engine.pivot_sort`` with random pivots; all segments of a level at once."""
    p, out = t.params, np.empty(len(t), np.int64)
    docs, at, bits = np.arange(len(t)), np.zeros(len(t), np.int64), len(t).bit_length()
    while len(docs):  # documents in order of segment and id; at: the place where a document's segment begins
        first = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        sizes, starts = np.diff(np.append(first, len(docs))), at[first]
        base = sizes <= p.list_size
        inside = np.repeat(base, sizes)
        own, n, segs = docs[inside], sizes[base], starts[base]
        name = lambda a, b, segs=segs, turn=turn: [f"{t.scope}:{phase}:{s}:{turn}:base:" for s in (segs[a:b] + seg).tolist()]
        got = yield from t.ranked(own, n, name, phase, "base", turn)
        out[np.repeat(segs, n) + ranges(n)] = got
        docs, n, segs = docs[~inside], sizes[~base], starts[~base]
        if not len(docs):
            break
        number = np.repeat(np.arange(len(n)), n)
        order = t.shuffled(docs, f"pivot{turn}", number)
        lead = order[ranges(n) < p.pivots]
        pivots = np.sort(docs[lead].reshape(-1, p.pivots), axis=1)
        ordered = yield from _settled(t, pivots, segs + seg, phase, turn)
        free = np.ones(len(docs), bool)
        free[lead] = False
        docs, number = docs[free], number[free]
        order = t.shuffled(docs, f"deal{turn}", number)
        docs, bucket = docs[order], np.zeros(len(docs), np.int64)  # the order within a segment; number stays as it is
        for g, a in enumerate(range(0, p.pivots, p.group)):
            bucket += yield from t.dealt(docs, n - p.pivots, ordered[:, a : a + p.group], segs + seg, g, phase, turn)
        counts = np.bincount(number * (p.pivots + 1) + bucket, minlength=len(n) * (p.pivots + 1)).reshape(len(n), -1)
        begins = segs[:, None] + np.cumsum(counts, axis=1) - counts + np.arange(p.pivots + 1)
        out[begins[:, 1:] - 1] = ordered
        both = np.sort((begins[number, bucket] << bits) | docs)
        docs, at = both & ((1 << bits) - 1), both >> bits
        turn += 1
    return out


def bracket(t: Table, k: int, seg: int = 0):
    """The first bracket of ``engine.tournament_topk``: documents with fewer than k known betters, the id known to be better than
    each (none: -1), and the bracket's levels."""
    size, heads, level = t.params.list_size, np.arange(len(t)), 0
    docs, root = heads, heads
    depth, better = np.zeros(len(t), np.int64), np.full(len(t), -1)
    place, lost, head = (np.zeros(len(t), np.int64) for _ in range(3))
    while len(heads) > 1:
        order = heads[t.shuffled(heads, f"0.{level}")]
        n = np.diff(np.append(np.arange(0, len(order), size), len(order)))
        name = lambda a, b, level=level: [f"{t.scope}:tournament:{seg}:0:bin:{level}.{j}" for j in range(a, b)]
        got = yield from t.ranked(order, n, name, "tournament", "bin", 0)
        p = ranges(n)
        place[got], head[got] = p, np.repeat(got[p == 0], n)
        lost[got] = np.where(p > 0, np.roll(got, 1), -1)
        depth, better, new = depth + place[root], np.where(better < 0, lost[root], better), head[root]
        keep = depth < k
        docs, root, depth, better = docs[keep], new[keep], depth[keep], better[keep]
        heads, level = np.sort(got[p == 0]), level + 1
    return docs, better, level


def filtered(t: Table, survivors: int, turn: int = 0):
    """``engine.bin_filter``."""
    size, docs = t.params.list_size, np.arange(len(t))
    order = t.shuffled(docs, str(turn))
    n = np.diff(np.append(np.arange(0, len(order), size), len(order)))
    name = lambda a, b: [f"{t.scope}:bin_filter:0:{turn}:bin:{j}" for j in range(a, b)]
    got = yield from t.ranked(order, n, name, "bin_filter", "bin", turn)
    return got[ranges(n) < survivors]
