"""Parameters and the schemas of internal tables. Total order everywhere: score descending, then id ascending."""

from __future__ import annotations

from dataclasses import dataclass, replace

ITEMS = "scope bigint, id bigint, payload string, score double, proxy double"
TOPK = "scope bigint, rank bigint, id bigint"
CALLS = "run_id string, algo string, scope bigint, round int, call_id string, kind string, n_items int, n_pivots int, chars_in bigint, repaired boolean, contradiction boolean"
PLAN = "use_filter boolean, s int, agg string, p_select int, p_sort int, n_after bigint, est_calls double, est_recall double"


@dataclass(frozen=True)
class RankParams:
    """list_size is L, pivots P, pivot_group P', survivors S.

    workers: at most so many lists are ranked at a time (one partition each), for a ranking service of that many
    instances; None leaves it to Spark. binning: how documents are dealt to lists (``binning.assign_bins``).
    """

    list_size: int = 20
    pivots: int = 4
    pivot_group: int | None = None
    early_stop: bool = False
    survivors: int = 1
    pivot_mode: str = "random"
    workers: int | None = None
    slot_order: str = "hash"
    binning: str = "exact"

    def __post_init__(self):
        if not 1 <= self.group <= self.pivots < self.list_size:
            raise ValueError("pivot groups and pivots must fit: 1 <= pivot_group <= pivots < list_size")
        if not 1 <= self.survivors < self.list_size:
            raise ValueError("survivors must be between 1 and list_size - 1")
        if self.pivot_mode not in ("random", "proxy"):
            raise ValueError("pivot_mode is random or proxy")
        if self.slot_order not in ("hash", "input") or self.binning not in ("exact", "balanced", "local"):
            raise ValueError("slot_order is hash or input, binning exact, balanced or local")

    @property
    def group(self) -> int:
        return self.pivots if self.pivot_group is None else self.pivot_group

    @classmethod
    def default(cls) -> RankParams:
        """The operating point of the experiments: lists of 20, 16 pivots in groups of 2, early stop."""
        return cls(list_size=20, pivots=16, pivot_group=2, early_stop=True)

    def but(self, **changes) -> RankParams:
        return replace(self, **changes)
