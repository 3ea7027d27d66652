"""The four algorithms over one scope that fits in a task: the tail of distributed runs, and the unit of simulation.

A ``Judge`` makes the calls and keeps the ledger. All shuffles and samples come from hashes of seed, round and id, so
a run's ledger depends on its inputs only, and a run that begins in Spark jobs goes on here with the same calls.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from ..schema import RankParams
from .kernel import answered, call_name, shuffled
from .prompts import buckets_from_response
from .rankers import ListRequest, Ranker

#: Documents from which pivots of a sort are picked by proxy.
SPREAD_SAMPLE = 1024


@dataclass
class Doc:
    id: int
    payload: str | None = None
    score: float | None = None
    proxy: float | None = None


@dataclass
class Judge:
    docs: dict[int, Doc]
    ranker: Ranker
    params: RankParams
    query: str = ""
    seed: int = 42
    scope: int = 0
    calls: list[dict] = field(default_factory=list)
    votes: int = 1

    def rank(self, ids: list[int], phase: str, kind: str, turn: int, pivots: int = 0, place: str = "", seg: int = 0) -> list[int]:
        """One call. Lists of one need none. With ``votes`` above 1 the call is repeated with other slots and mean places decide."""
        if len(ids) < 2:
            return list(ids)
        if len(ids) > self.params.list_size:
            raise ValueError(f"a list of {len(ids)} is longer than {self.params.list_size}")
        own = [self.docs[i] for i in ids]
        name = call_name(self.scope, phase, seg, turn, kind, place)
        request = ListRequest(name, list(ids), [d.payload for d in own], [d.score for d in own], self.query, pivots)
        order, repaired, contradicted = answered(self.ranker, [request], self.seed, self.params, self.votes)[0]
        for vote in range(self.votes):
            self.calls.append({"algo": phase, "scope": self.scope, "round": turn, "call_id": name if self.votes == 1 else f"{name}#{vote}", "kind": kind, "n_items": len(ids), "n_pivots": pivots, "chars_in": sum(len(d.payload or "") for d in own), "repaired": repaired[vote], "contradiction": contradicted[vote]})
        return [ids[p] for p in order]


def tournament_topk(judge: Judge, ids: list[int], k: int, bins: list[list[int]] | None = None, beaten: dict[int, set[int]] | None = None, edge_mode: str = "chain", step: int = 0, seg: int = 0) -> list[int]:
    """The k best in order: the winner of a tournament among documents that nobody live is known to beat, k times.

    edge_mode: a ranked list is kept as a chain of neighbours or as all its pairs (complete); a document placed p-th is
    free once the p - 1 above it are gone under either, so results and calls are the same and the chain is smaller.
    beaten: documents known better than a document, from a bracket that already ran ``step`` levels. bins: the first round's bins, for fixed traces.
    seg: documents before these, which names the segment of a full sort.
    """
    size = judge.params.list_size
    better: dict[int, set[int]] = {i: set(beaten.get(i, ())) if beaten else set() for i in ids}
    worse: dict[int, set[int]] = {}
    for i, above in better.items():
        for b in above:
            worse.setdefault(b, set()).add(i)
    free = {i for i, above in better.items() if not above}
    out: list[int] = []
    for turn in range(min(k, len(ids))):
        field_ = list(free)
        lists, level = bins if turn == 0 and bins else None, 0 if turn else step
        while len(field_) > 1:
            order = shuffled(field_, judge.seed, f"{turn}.{level}")
            heads = []
            for number, own in enumerate(lists or [order[i : i + size] for i in range(0, len(order), size)]):
                ranked = judge.rank(own, "tournament", "bin", turn, place=f"{level}.{number}", seg=seg)
                known = zip(ranked, ranked[1:], strict=False) if edge_mode == "chain" else ((a, b) for i, a in enumerate(ranked) for b in ranked[i + 1 :])
                for a, b in known:
                    better[b].add(a)
                    free.discard(b)
                    worse.setdefault(a, set()).add(b)
                heads.append(ranked[0])
            field_, lists, level = heads, None, level + 1
        winner = field_[0]
        out.append(winner)
        for d in worse.pop(winner, ()):
            if d in better:
                better[d].discard(winner)
                if not better[d]:
                    free.add(d)
        del better[winner]
        free.discard(winner)
    return out


def _pivots(judge: Judge, ids: list[int], count: int, wanted: int, turn: int, spread: bool) -> list[int]:
    """Random pivots, or by proxy: around the wanted rank for selection, evenly spread over a sample for sorting."""
    mixed = shuffled(ids, judge.seed, f"pivot{turn}")
    if judge.params.pivot_mode == "random":
        return sorted(mixed[:count])
    order = sorted(mixed[:SPREAD_SAMPLE] if spread else ids, key=lambda i: (-(judge.docs[i].proxy or 0.0), i))
    n = len(order)
    if spread:
        return sorted({order[min(n - 1, (j + 1) * n // (count + 1))] for j in range(count)})
    start = max(0, min(wanted - 1, n - count))
    return sorted(order[start : start + count])


def _deal(judge: Judge, ids: list[int], pivots: list[int], turn: int, wanted: int | None, phase: str, seg: int = 0) -> tuple[list[list[int]], list[int]]:
    """Buckets 0..P, best first, and the pivots in settled order. ``wanted``: with early stop, ranks that still matter."""
    p = judge.params
    stop = p.early_stop and wanted is not None
    ordered = judge.rank(pivots, phase, "pivots", turn, seg=seg) if len(pivots) > 1 else pivots
    groups = [ordered[i : i + p.group] for i in range(0, len(ordered), p.group)]
    bucket = {}
    rest = shuffled([i for i in ids if i not in set(pivots)], judge.seed, f"deal{turn}")
    below = dict.fromkeys(rest, 0)
    used, room = 0, p.list_size - p.group
    for number, group in enumerate(groups):
        asked = [i for i in rest if i not in bucket] if stop else rest
        for at in range(0, len(asked), room):
            own = asked[at : at + room]
            found, _ = buckets_from_response(judge.rank([*group, *own], phase, "bucket", turn, len(group), f"{number}.{at // room}", seg), group)
            for d, b in found.items():
                below[d] += b
                if stop and b < len(group):
                    bucket[d] = used + b
        used += len(group)
        if stop and number + 1 < len(groups) and len(bucket) + used >= wanted:
            ordered = ordered[:used]
            break
    for d in rest:
        bucket.setdefault(d, used if stop else below[d])
    out: list[list[int]] = [[] for _ in range(len(ordered) + 1)]
    for d in rest:
        out[bucket[d]].append(d)
    # pivots of groups that were never asked lie below the last one that was
    out[-1] += [x for g in groups for x in g if x not in set(ordered)]
    return out, ordered


def pivot_select(judge: Judge, ids: list[int], k: int, pivots: list[int] | None = None, turn: int = 0) -> list[int]:
    """The k best, in no order. pivots: the first round's, for fixed traces. turn: rounds that went before."""
    p, left, out = judge.params, min(k, len(ids)), []
    ids = list(ids)
    while left > 0:
        if left >= len(ids):
            return [*out, *ids]
        if len(ids) <= p.list_size and not pivots:
            return [*out, *judge.rank(sorted(ids), "select", "base", turn)[:left]]
        chosen = pivots or _pivots(judge, ids, min(p.pivots, len(ids) - 1), left, turn, False)
        dealt, ordered = _deal(judge, ids, chosen, turn, left, "select")
        ids, pivots = [], None
        for i, own in enumerate(dealt):
            if len(own) > left:
                ids = own
                break
            out += own
            left -= len(own)
            if left and i < len(ordered):
                out.append(ordered[i])
                left -= 1
            if not left:
                break
        turn += 1
    return out


def pivot_sort(judge: Judge, ids: list[int], pivots: list[int] | None = None, turn: int = 0, seg: int = 0, phase: str = "sort") -> list[int]:
    """All documents, best first. seg: documents before these, which names the segment."""
    if len(ids) < 2:
        return list(ids)
    if len(ids) <= judge.params.list_size and not pivots:
        return judge.rank(sorted(ids), phase, "base", turn, seg=seg)
    chosen = pivots or _pivots(judge, ids, min(judge.params.pivots, len(ids) - 1), 0, turn, True)
    dealt, ordered = _deal(judge, ids, chosen, turn, None, phase, seg)
    out: list[int] = []
    for i, own in enumerate(dealt):
        out += pivot_sort(judge, own, turn=turn + 1, seg=seg + len(out), phase=phase)
        if i < len(ordered):
            out.append(ordered[i])
    return out


def bin_filter(judge: Judge, ids: list[int], survivors: int, bins: list[list[int]] | None = None, turn: int = 0) -> list[int]:
    """The best ``survivors`` of each bin of one round."""
    size = judge.params.list_size
    order = shuffled(ids, judge.seed, turn)
    return [i for n, own in enumerate(bins or [order[j : j + size] for j in range(0, len(order), size)]) for i in judge.rank(own, "bin_filter", "bin", turn, place=str(n))[:survivors]]


def refine_top(judge: Judge, ranked: list[int], m: int = 10) -> list[int]:
    """The first m again, by pairwise quicksort."""
    pair = Judge(judge.docs, judge.ranker, pairwise(judge.params), judge.query, judge.seed, judge.scope, judge.calls, judge.votes)
    return [*pivot_sort(pair, ranked[:m], phase="refine"), *ranked[m:]]


def pairwise(params: RankParams) -> RankParams:
    return params.but(list_size=2, pivots=1, pivot_group=None, survivors=1, early_stop=False, pivot_mode="random")
