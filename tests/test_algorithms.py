"""Worked examples, invariants under a perfect ranker, costs, errata and the planner."""

import json
import math
import random
import statistics

import numpy as np
import pytest

from semrank.operators.engine import Doc, Judge, bin_filter, pivot_select, pivot_sort, refine_top, tournament_topk
from semrank.operators.prompts import build_listwise_prompt, buckets_from_response, parse_ranking, repair_ranking
from semrank.operators.rankers import BrokenRanker, CachingRanker, ColumnRanker, ContradictingRanker, HttpRanker, LexicalRanker, ListRequest, NoisyRanker, PointScorer, VectorRanker, parse_score
from semrank.plans import cost, planner, simulate
from semrank.schema import RankParams

TOY = [2, 6, 4, 5, 1, 3]
SMALL = RankParams(list_size=3, pivots=2, survivors=2)


def judge(n_or_ids, params=None, ranker=None, seed=42, votes=1):
    ids = range(n_or_ids) if isinstance(n_or_ids, int) else n_or_ids
    docs = {i: Doc(i, score=float(i) if not isinstance(n_or_ids, int) else float((i * 7919) % max(1, len(ids))), proxy=float(i)) for i in ids}
    return Judge(docs, ranker or ColumnRanker(), params or RankParams(), seed=seed, votes=votes), list(docs)


def truth(j):
    return sorted(j.docs, key=lambda i: (-j.docs[i].score, i))


@pytest.mark.parametrize("bins", [[[2, 6, 4], [5, 1, 3]], [[4, 5, 6], [1, 2, 3]]])
def test_toy_tournament(bins):
    j, ids = judge(TOY, SMALL)
    assert tournament_topk(j, ids, 2, bins) == [6, 5] and len(j.calls) == 4


def test_toy_select_sort_filter_and_early_stop():
    j, ids = judge(TOY, SMALL)
    assert set(pivot_select(j, ids, 2, [2, 6])) == {5, 6} and len(j.calls) == 6
    j, ids = judge(TOY, SMALL.but(pivot_group=1, early_stop=True))
    assert pivot_select(j, ids, 1, [2, 6]) == [6]
    assert [c["kind"] for c in j.calls] == ["pivots", "bucket", "bucket"]  # the second group is never asked
    j, ids = judge(TOY, SMALL)
    assert pivot_sort(j, ids, [2, 6]) == [6, 5, 4, 3, 2, 1]
    j, ids = judge(TOY, SMALL)
    kept = bin_filter(j, ids, 2, [[4, 5, 6], [1, 2, 3]])
    assert set(kept) == {6, 5, 3, 2}
    assert [len(set(kept) & set(range(7 - k, 7))) / k for k in (1, 2, 3)] == [1, 1, 2 / 3]


@pytest.mark.parametrize("n", [0, 1, 5, 19, 20, 21, 300])
@pytest.mark.parametrize("params", [RankParams(), RankParams(pivots=1), RankParams.default(), RankParams(pivots=8, pivot_group=2), RankParams(pivot_mode="proxy"), RankParams(list_size=2, pivots=1), RankParams(list_size=5, pivots=4, pivot_group=1, early_stop=True)])
def test_a_perfect_ranker_gives_the_exact_answer(n, params):
    for k in {0, 1, n // 2, n, n + 1}:
        j, ids = judge(n, params)
        want = truth(j)[:k]
        assert sorted(pivot_select(j, ids, k)) == sorted(want)
        j, ids = judge(n, params)
        assert tournament_topk(j, ids, k) == want
    j, ids = judge(n, params)
    assert pivot_sort(j, ids) == truth(j)


def test_chain_and_complete_edges_agree():
    (a, ids), (b, _) = judge(700), judge(700)
    assert tournament_topk(a, ids, 12) == tournament_topk(b, ids, 12, edge_mode="complete") and a.calls == b.calls


def test_sizes_that_need_no_call():
    j, ids = judge(1)
    assert pivot_sort(j, ids) == ids and pivot_select(j, ids, 1) == ids and tournament_topk(j, ids, 1) == ids and not j.calls
    j, ids = judge(20)
    pivot_select(j, ids, 5)
    assert len(j.calls) == 1


def test_same_seed_same_ledger():
    a, ids = judge(500, RankParams.default())
    b, _ = judge(500, RankParams.default())
    pivot_select(a, ids, 10), pivot_select(b, list(reversed(ids)), 10)
    assert a.calls == b.calls


def test_early_stop_needs_fewer_calls():
    mean = lambda p: statistics.mean(len((pivot_select((x := judge(3000, p, seed=s))[0], x[1], 10), x[0].calls)[1]) for s in range(8))
    whole, stopped, no_stop = (mean(RankParams(20, 16, g, e)) for g, e in ((16, False), (2, True), (2, False)))
    assert stopped < whole < no_stop
    assert mean(RankParams(20, 8, 2, True)) < mean(RankParams(20, 4))


def test_contradictions_and_broken_responses():
    assert buckets_from_response([1, 99, 2], [2, 1]) == ({99: 1}, True)
    assert repair_ranking([1, 1, 9, 3], 4) == ([1, 3, 2, 4], True)
    assert parse_ranking("[3] > [1] > [2]") == [3, 1, 2] and parse_ranking(None) == []
    j, ids = judge(200, ranker=BrokenRanker(ColumnRanker()))
    assert sorted(pivot_sort(j, ids)) == ids and any(c["repaired"] for c in j.calls)
    j, ids = judge(200, ranker=ContradictingRanker(ColumnRanker(), 0.5))
    got = pivot_select(j, ids, 20)
    assert len(set(got)) == 20 and any(c["contradiction"] for c in j.calls)


def test_prompts_and_scores():
    text = build_listwise_prompt("q", ["a", "b"], ["p"])
    assert "[1] p\n[2] a\n[3] b" in text
    assert [parse_score(t, 100) for t in ("87", " 12.5 ", "n/a", "", "nan", "inf", "1_000", "1e2")] == [(87, True), (12.5, True), (50, False), (50, False), (50, False), (50, False), (50, False), (100, True)]
    r = ListRequest("c", [1, 2, 3], ["cat dog", "cat", "bird"], [1.0, 2.0, None], "dog cat")
    assert LexicalRanker().rank([r]) == [[0, 1, 2]] and ColumnRanker().rank([r]) == [[1, 0, 2]]
    v = ListRequest("c", [1, 2], ["[1, 0]", "[0, 1]"], [None, None])
    assert VectorRanker([0.0, 2.0]).rank([v]) == [[1, 0]]
    cached = CachingRanker(ColumnRanker())
    assert cached.rank([r]) == cached.rank([r]) and cached.hits == 1
    assert PointScorer(ColumnRanker(), 5, 1.0).respond(r) == "n/a"


def test_noise_lowers_accuracy_and_votes_raise_it():
    def overlap(sigma, votes=1):
        out = []
        for s in range(5):
            j, ids = judge(300, ranker=NoisyRanker(ColumnRanker(), sigma, s), seed=s, votes=votes)
            out.append(len(set(pivot_select(j, ids, 20)) & set(truth(j)[:20])))
        return statistics.mean(out)

    assert overlap(0) == 20 > overlap(10) > overlap(200)
    assert overlap(100, votes=5) > overlap(100)


def test_refine_top_repairs_the_first():
    j, ids = judge(50)
    bad = truth(j)
    random.Random(1).shuffle(bad[:10])
    assert refine_top(j, bad, 10)[:10] == sorted(bad[:10], key=lambda i: -j.docs[i].score)


def test_filter_recall_forms():
    assert cost.recall_filter(5183, 10, 20, 1, "printed") > 1
    for k, s, want in ((10, 1, 0.981), (50, 1, 0.9094), (50, 2, 0.9944)):
        assert cost.recall_filter(5183, k, 20, s) == pytest.approx(want, abs=1e-3)
        rng = np.random.default_rng(1)
        run = statistics.mean(simulate.filter_recall(rng, 5183, k, 20, s) for _ in range(1500))
        assert cost.recall_filter(5183, k, 20, s, "exact") == pytest.approx(run, abs=0.006)


def test_tournament_cost_forms():
    for n, k, calls in ((1000, 10, 63.0), (1000, 100, 153.0), (5183, 10, 283.0)):
        j, ids = judge(n)
        tournament_topk(j, ids, k)
        assert len(j.calls) == pytest.approx(calls, abs=4)
        assert cost.cost_tournament(n, k, 20) == pytest.approx(len(j.calls), rel=0.05)
    assert cost.cost_tournament(1000, 100, 20, "remark") < 70 and cost.cost_tournament(1000, 100, 20, "summary") > 400


def test_best_pivots():
    assert cost.best_p_sort(20) == 6 and cost.best_p_select(1000, 1, 20) == 4
    root = 6.1
    assert abs(cost.sort_condition(root, 20)) < 0.1
    assert round(math.sqrt(1 + 20) - 1, 2) == 3.58
    s = cost.min_survivors(5183, 50, 20, 0.95)
    assert s == next(x for x in range(1, 20) if cost.recall_filter(5183, 50, 20, x) >= 0.95)


def test_simulation_against_theory():
    rng = np.random.default_rng(7)
    for p in (2, 4, 6, 8, 12):
        run = statistics.mean(simulate.sort_calls(rng, 1000, 20, p) for _ in range(150))
        assert cost.cost_sort(1000, 20, p) == pytest.approx(run, rel=0.12)
    for k, p in ((1, 2), (1, 4), (10, 4), (100, 6)):
        run = statistics.mean(simulate.select_calls(rng, 1000, k, 20, p) for _ in range(300))
        assert cost.cost_select(1000, k, 20, p) == pytest.approx(run, rel=0.13)
    exact = simulate.exact_select_cost(120, 10, 20, 4)
    assert exact == pytest.approx(statistics.mean(simulate.select_calls(rng, 120, 10, 20, 4) for _ in range(4000)), rel=0.03)


def test_simulated_calls_are_those_of_runs():
    runs = [(x := judge(2000, RankParams(20, 8, 2, True), seed=s), pivot_select(*x, 10), len(x[0].calls))[2] for s in range(25)]
    rng = np.random.default_rng(1)
    assert statistics.mean(runs) == pytest.approx(statistics.mean(simulate.select_calls(rng, 2000, 10, 20, 8, 2, True) for _ in range(400)), rel=0.06)


def test_planner():
    plans = planner.all_plans(5183, 10, 20, 0.95)
    best = planner.choose_plan(5183, 10, 20, 0.95)
    assert len(plans) == 4 and best.est_calls == min(p.est_calls for p in plans)
    by = {(p.use_filter, p.agg): p.est_calls for p in plans}
    assert by[False, "tournament"] == pytest.approx(281.7, abs=1) and by[True, "pivot"] == pytest.approx(282, rel=0.02) and by[True, "tournament"] == pytest.approx(283, rel=0.02)
    assert not any(p.use_filter for p in planner.all_plans(1000, 900, 20, 0.5))  # too few would be left
    assert {p.agg for p in planner.all_plans(256, 256, 20, mode="sort")} == {"tournament", "pivot"}
    assert planner.choose_plan(10, 3).est_calls <= 2
    assert planner.estimate_seconds(100, 0.5, 10) == 5.0


def test_bad_parameters():
    for bad in ({"pivots": 20}, {"pivots": 4, "pivot_group": 5}, {"survivors": 20}, {"pivot_mode": "x"}):
        with pytest.raises(ValueError):
            RankParams(**bad)


def test_http_ranker_sends_whole_texts():
    sent = []

    class Service(HttpRanker):
        def _post(self, body):
            sent.extend(json.loads(body)["prompts"])
            return {"responses": ["[2] > [1]"]}

    request = ListRequest("q", [1, 2], ["a" * 9000 + "end of a", "b"], [0.0, 0.0])
    assert Service("http://none", "m").rank([request]) == [[1, 0]] and "a" * 9000 + "end of a" in sent[0]
    Service("http://none", "m", max_chars=10).rank([request])
    assert "a" * 11 not in sent[1]


def test_http_ranker_against_a_service():
    """A local service that orders passages by length and fails at first: pivots in the prompt, retries, answers remembered and forgotten."""
    import threading
    from http.server import BaseHTTPRequestHandler, HTTPServer

    seen = []

    class Service(BaseHTTPRequestHandler):
        def do_POST(self):  # noqa: N802
            asked = json.loads(self.rfile.read(int(self.headers["Content-Length"])))
            seen.append(asked)
            if len(seen) == 1:
                self.send_error(503)
                return
            answers = []
            for prompt in asked["prompts"]:
                lines = [x for x in prompt.split("\n") if x.startswith("[")]
                answers.append(" > ".join(x.split("]")[0] + "]" for x in sorted(lines, key=len, reverse=True)))
            body = json.dumps({"responses": answers}).encode()
            self.send_response(200)
            self.send_header("Content-Length", str(len(body)))
            self.end_headers()
            self.wfile.write(body)

        def log_message(self, *_):
            pass

    server = HTTPServer(("127.0.0.1", 0), Service)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    try:
        ranker = HttpRanker(f"http://127.0.0.1:{server.server_port}", "m", pause=0.01, remember=2)
        request = ListRequest("c", [5, 6, 7], ["a", "a" * 30, "a" * 9], [None] * 3, "q", 2)
        assert ranker.rank([request]) == [[1, 2, 0]] and len(seen) == 2
        assert "Passages 1 to 2 are already listed" in seen[1]["prompts"][0]
        assert ranker.rank([request]) == [[1, 2, 0]] and len(seen) == 2
        ranker.rank([ListRequest("d", [i, i + 1], ["b", "bb"], [None] * 2, "q") for i in (1, 2, 3)])
        assert len(ranker._known) == 2
        ranker.rank([request])
        assert len(seen) == 4
        j = Judge({i: Doc(i, "w" * (i + 1)) for i in range(60)}, ranker, RankParams(), "q")
        assert set(pivot_select(j, list(range(60)), 7)) == set(range(53, 60))
    finally:
        server.shutdown()


def test_workloads_have_their_published_size(monkeypatch):
    """25 queries over the whole corpus, 5,000 trials a point."""
    from semrank.plans import catalog, experiments

    asked, trials = [], []
    monkeypatch.setattr(experiments, "claim_items", lambda s, d, n_queries=experiments.QUERIES, n_docs=None: asked.append((n_queries, n_docs)))
    for name in ("sweep_list_size", "sweep_k", "sweep_p"):
        monkeypatch.setattr(experiments, name, lambda items: None)
    monkeypatch.setattr(simulate, "compare_theory", lambda s, algo, grid, n: trials.append(n))
    monkeypatch.setattr(simulate, "simulate_grid", lambda s, algo, grid, n: trials.append(n))
    for name in ("w_list_size", "w_k", "w_pivots", "simulate_select", "simulate_sort", "simulate_filter", "simulate_tournament", "simulate_pivot_groups"):
        catalog.QUERIES[name](None, "")
    assert asked == [(25, None)] * 3 and trials == [5_000] * 5
