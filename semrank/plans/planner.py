"""Choosing among the four plans, running the choice, and explaining it."""

from __future__ import annotations

from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession

from ..operators import topk
from ..operators.kernel import Ranked
from ..operators.rankers import Ranker
from ..schema import PLAN, RankParams
from . import cost


@dataclass(frozen=True)
class Plan:
    use_filter: bool
    s: int
    agg: str
    p_select: int
    p_sort: int
    n_after: int
    est_calls: float
    est_recall: float


def all_plans(n: int, k: int, size: int, target: float = 0.95, mode: str = "topk", model: str = "poisson") -> list[Plan]:
    """Every plan that meets the recall target. A full sort has neither filter nor select."""
    k = min(k, n)
    p_sort = cost.best_p_sort(size) if size > 2 else 1
    if mode == "sort" or k >= n:
        return [Plan(False, 0, "tournament", 0, 0, n, cost.cost_tournament(n, n, size), 1.0), Plan(False, 0, "pivot", 0, p_sort, n, cost.cost_sort(n, size, p_sort), 1.0)]
    out = []
    s = cost.min_survivors(n, k, size, target, model) if n > size else None
    for use_filter in (False, True):
        if use_filter and (s is None or cost.n_after_filter(n, size, s) < k or topk.survivor_count(n, size, s) < k):
            continue
        left = cost.n_after_filter(n, size, s) if use_filter else n
        before = cost.cost_filter(n, size) if use_filter else 0
        recall = cost.recall_filter(n, k, size, s, model) if use_filter else 1.0
        p = cost.best_p_select(left, k, size)
        out.append(Plan(use_filter, s if use_filter else 0, "tournament", 0, 0, left, before + cost.cost_tournament(left, k, size), recall))
        out.append(Plan(use_filter, s if use_filter else 0, "pivot", p, p_sort, left, before + cost.cost_select(left, k, size, p) + cost.cost_sort(k, size, p_sort), recall))
    return out


def choose_plan(n: int, k: int, size: int = 20, target: float = 0.95, mode: str = "topk", model: str = "poisson") -> Plan:
    """The cheapest; of equal ones that with fewer rounds: pivot plans before tournaments, without filter first."""
    return min(all_plans(n, k, size, target, mode, model), key=lambda p: (round(p.est_calls, 9), p.agg != "pivot", p.use_filter))


def explain_semantic(spark: SparkSession, n: int, k: int, size: int = 20, target: float = 0.95, mode: str = "topk") -> DataFrame:
    """The plans that were weighed, cheapest first, for an outer optimiser to read."""
    plans = sorted(all_plans(n, k, size, target, mode), key=lambda p: p.est_calls)
    return spark.createDataFrame([tuple(asdict(p).values()) for p in plans], PLAN)


def estimate_seconds(calls: float, list_seconds: float, workers: int = 1, rounds: int = 1) -> float:
    """Waves of parallel calls, each as long as one list takes, and at least one wave a round."""
    return max(rounds, calls / workers) * list_seconds


def operating_point_calls(spark: SparkSession, n: int, k: int, params: RankParams | None = None, trials: int = 500) -> float:
    """Mean calls of select, then sort, with pivot groups and early stop, for which there is no closed form: by simulation."""
    from . import simulate

    p = params or RankParams.default()
    chosen = simulate.simulate_grid(spark, "select", [{"n": n, "k": min(k, n), "size": p.list_size, "p": p.pivots, "group": p.group, "early_stop": p.early_stop}], trials).first()["value"]
    return chosen + cost.cost_sort(min(k, n), p.list_size, p.pivots) if k > p.list_size else chosen + 1.0 * (k > 1)


def execute_plan(plan: Plan, items: DataFrame, k: int, ranker: Ranker, size: int = 20, seed: int = 42, queries: DataFrame | None = None, refine: int = 0, override: RankParams | None = None, tail: int = topk.TAIL) -> Ranked:
    """override: the pivots, groups and early stop of the experiments instead of the plan's."""
    base = override or RankParams(list_size=size, pivots=max(1, plan.p_select or plan.p_sort or 1), survivors=max(1, plan.s))
    calls = []
    if plan.use_filter:
        kept = topk.bin_filter(items, ranker, base.but(survivors=plan.s), seed, queries=queries, least=0)
        items = kept.rows
        calls.append(kept.calls)
    if plan.agg == "tournament":
        done = topk.tournament(items, k, ranker, base, seed, queries, tail)
    elif plan.p_select == 0 and override is None:
        done = topk.sort(items, ranker, base.but(pivots=plan.p_sort), seed, queries, tail)
        done = Ranked(done.rows.filter(f"rank <= {k}"), done.calls)
    else:
        done = topk.pivot_topk(items, k, ranker, base, seed, queries, tail, refine, plan.p_sort or None)
    return Ranked(done.rows, topk._joined([*calls, done.calls]))
