"""Prompts for listwise calls, and what comes back: parsing, repair, and the contradiction rule."""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F


def build_listwise_prompt(query: str, docs: list[str], pivots: list[str] | None = None) -> str:
    """A numbered list; pivots come first, in their settled order."""
    listed = [*(pivots or []), *docs]
    lines = [f"[{i}] {text}" for i, text in enumerate(listed, 1)]
    known = f"\nPassages 1 to {len(pivots)} are already listed from best to worst." if pivots else ""
    return f"Order the passages by relevance to: {query}{known}\n" + "\n".join(lines) + "\nAnswer with all numbers, most relevant first."


def prompt_column(query: Column, docs: Column) -> Column:
    """The same prompt without pivots, as a column over an array of texts."""
    lines = F.transform(docs, lambda x, i: F.concat(F.lit("["), (i + 1).cast("string"), F.lit("] "), x))
    return F.concat(F.lit("Order the passages by relevance to: "), query, F.lit("\n"), F.array_join(lines, "\n"), F.lit("\nAnswer with all numbers, most relevant first."))


def parse_ranking(text: str | None) -> list[int]:
    """Every number of the response in order."""
    return [int(x) for x in re.findall(r"\d+", text or "")]


def repair_ranking(positions: list[int], n: int) -> tuple[list[int], bool]:
    """Positions 1..n once each: unknown and repeated ones go, missing ones follow in input order. Second: whether that changed anything."""
    seen: dict[int, None] = {}
    for p in positions:
        if 1 <= p <= n:
            seen.setdefault(p, None)
    fixed = [*seen, *(p for p in range(1, n + 1) if p not in seen)]
    return fixed, fixed != list(positions)


def repair_column(positions: Column, n: Column) -> Column:
    """``repair_ranking`` as a column."""
    known = F.filter(F.array_distinct(positions), lambda p: (p >= 1) & (p <= n))
    return F.concat(known, F.array_except(F.sequence(F.lit(1), n), known))


def buckets_from_response(ranked: list[int], pivots: list[int]) -> tuple[dict[int, int], bool]:
    """Bucket of each document: how many pivots stand before it, whichever they are. The settled order of pivots wins."""
    place = {p: i for i, p in enumerate(pivots)}
    met, buckets, seen = 0, {}, []
    for d in ranked:
        if d in place:
            met += 1
            seen.append(place[d])
        else:
            buckets[d] = met
    return buckets, seen != sorted(seen)


def bucket_column(ranked: Column, pivots: Column) -> Column:
    """An array of (id, bucket) of the documents of a response, best first."""
    flagged = F.transform(ranked, lambda d: F.struct(d.alias("id"), F.array_contains(pivots, d).alias("is_pivot")))
    counted = F.transform(flagged, lambda x, i: F.struct(x["id"].alias("id"), x["is_pivot"].alias("is_pivot"), F.size(F.filter(F.slice(flagged, F.lit(1), i + 1), lambda y: y["is_pivot"])).alias("bucket")))
    return F.transform(F.filter(counted, lambda x: ~x["is_pivot"]), lambda x: F.struct(x["id"].alias("id"), x["bucket"].alias("bucket")))


def clip_payload(payload: Column, max_chars: int) -> Column:
    return F.substring(payload, 1, max_chars)
