"""Skeletons as text and as (types, breaks), their sub-patterns, candidates and rendering."""

from __future__ import annotations

from math import ceil, comb

from relseq.operators.corpus import BREAK, SAME

Skeleton = tuple[tuple[str, ...], tuple[bool, ...]]  # types, and whether a separator follows each but the last


def parse(text: str) -> Skeleton:
    types: list[str] = []
    breaks: list[bool] = []
    for n, block in enumerate(text.split(BREAK)):
        for m, t in enumerate(block.split(SAME)):
            if types:
                breaks.append(m == 0 and n > 0)
            types.append(t)
    return tuple(types), tuple(breaks)


def render(s: Skeleton) -> str:
    types, breaks = s
    return types[0] + "".join((BREAK if b else SAME) + t for t, b in zip(types[1:], breaks)) if types else ""


def drop(s: Skeleton, i: int) -> Skeleton:
    """The skeleton without event ``i``; a separator on either side of an inner event stays."""
    types, breaks = s
    if i == 0:
        return types[1:], breaks[1:]
    if i == len(types) - 1:
        return types[:-1], breaks[:-1]
    return types[:i] + types[i + 1 :], breaks[: i - 1] + (breaks[i - 1] or breaks[i],) + breaks[i + 1 :]


def safe_subpatterns(s: Skeleton, gapped: bool) -> list[Skeleton]:
    """Sub-patterns that are at least as frequent: all with one event less, or the two trimmed ones if gaps are
    limited (leaving out an inner event widens a gap)."""
    k = len(s[0])
    return [drop(s, i) for i in ((0, k - 1) if gapped else range(k))]


def extend(frequent: set[Skeleton], gapped: bool, drop_runs: int | None = None) -> list[Skeleton]:
    """Candidates with one event more than ``frequent``, all of one length."""
    if not frequent:
        return []
    if len(next(iter(frequent))[0]) == 1:
        names = sorted(t[0] for t, _ in frequent)
        found = {((a, b), (brk,)) for a in names for b in names for brk in (False, True) if brk or a <= b}
    else:
        by_head: dict[Skeleton, list[Skeleton]] = {}
        for s in frequent:
            by_head.setdefault(drop(s, len(s[0]) - 1), []).append(s)
        found = set()
        for s in frequent:
            for t in by_head.get(drop(s, 0), ()):
                found.add((s[0] + t[0][-1:], s[1] + t[1][-1:]))
    found = {s for s in found if all(p in frequent for p in safe_subpatterns(s, gapped))}
    if drop_runs:
        found = {s for s in found if longest_run(s) < drop_runs}
    return sorted(found)


def longest_run(s: Skeleton) -> int:
    best = run = 0
    last = None
    for t in s[0]:
        run = run + 1 if t == last else 1
        best, last = max(best, run), t
    return best


def need(s: Skeleton) -> dict[str, int]:
    out: dict[str, int] = {}
    for t in s[0]:
        out[t] = out.get(t, 0) + 1
    return out


def threshold(min_support: float, n: int, strict: bool = False) -> int:
    """Sequences needed: a count as it is, a fraction of ``n`` rounded up."""
    t = min_support if min_support >= 1 else ceil(min_support * n - 1e-9)
    return int(t) + 1 if strict else max(1, int(ceil(t)))


def describe(s: Skeleton, slots: list[str], vector: list[str]) -> str:
    """Events in order; after each what is known of it and of its relations to earlier events."""
    types, breaks = s
    known: dict[int, list[str]] = {}
    for name, concept in zip(slots, vector):
        if concept:
            where, _, tree = name.partition(".")
            j, _, i = where.rpartition("-")
            known.setdefault(int(i), []).append(f"{concept} to {j}" if j else concept)
    parts = [t + (f"({', '.join(known[i])})" if i in known else "") for i, t in enumerate(types, 1)]
    return parts[0] + "".join((BREAK if b else SAME) + p for p, b in zip(parts[1:], breaks))


# -- bounds -------------------------------------------------------------------------------------------------


def occurrence_bound(n: int, k: int, gap: int | None = None, span: int | None = None, form: str = "corrected") -> int:
    """Upper bound of the occurrences of a k-event skeleton in n events: unconstrained, by gap or by span.

    ``published`` gives the forms as they were printed, which are too small in corner cases.
    """
    start = n - k if form == "published" else n - k + 1
    if gap is not None:
        return (gap - 1 if form == "published" else gap) ** (k - 1) * max(start, 0)
    if span is not None:
        return comb(span, k - 1) * max(start, 0)
    return comb(n, k)


def step_bound(n: int, k: int, gap: int | None = None, span: int | None = None, form: str = "corrected") -> int:
    return k * occurrence_bound(n, k, gap, span, form)


def presence_bound(n: int, gapped: bool) -> int:
    """Steps to find whether a skeleton occurs at all."""
    return n * n if gapped else n


def check_constraint(accepts, universe: list[Skeleton], gapped: bool = False) -> None:
    """Refuses a mining constraint that a pattern can satisfy while one of its safe sub-patterns does not."""
    for s in universe:
        if len(s[0]) > 1 and accepts(s) and not all(accepts(p) for p in safe_subpatterns(s, gapped)):
            raise ValueError(f"not usable while mining: {render(s)!r} passes, but a sub-pattern of it does not; filter the result instead")
