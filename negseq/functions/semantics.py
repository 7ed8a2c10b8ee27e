"""When is an absence pattern found in a sequence: three switches and two constraints.

Plain Python, for runtime patterns in Arrow functions and as a reference; the column
form is in operators.matching. Positions count from 1.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

from .pattern import Pattern


@dataclass(frozen=True)
class Semantics:
    non_inclusion: str = "total"
    embedding: str = "soft"
    occurrence: str = "soft"

    def __post_init__(self) -> None:
        if self.non_inclusion not in ("total", "partial") or self.embedding not in ("soft", "strict") or self.occurrence not in ("soft", "strict"):
            raise ValueError(f"unknown semantics {self}")


@dataclass(frozen=True)
class Constraints:
    """maxgap: consecutive positive positions differ by at most this; maxspan: the last and the first."""

    maxgap: int | None = None
    maxspan: int | None = None

    def __post_init__(self) -> None:
        if (self.maxgap is not None and self.maxgap < 1) or (self.maxspan is not None and self.maxspan < 0):
            raise ValueError("maxgap is at least 1 and maxspan at least 0")


GROWTH = Semantics()
PARTNER_ITEM = Semantics("total", "soft", "strict")
PARTNER_ITEMSET = Semantics("partial", "soft", "strict")
LEGACY_TOTAL = Semantics("total", "soft", "soft")
#: Absences of one item only.
LEGACY_ITEM = Semantics("total", "soft", "soft")
ALL = tuple(Semantics(a, b, c) for a in ("total", "partial") for b in ("soft", "strict") for c in ("soft", "strict"))
FREE = Constraints()


def absent(q: frozenset, itemset: frozenset, non_inclusion: str) -> bool:
    return not q & itemset if non_inclusion == "total" else not q <= itemset


def window_ok(q: Sequence[str], window: Sequence[frozenset], sem: Semantics) -> bool:
    """Whether the itemsets strictly between two positives lack q."""
    if not q:
        return True
    q = frozenset(q)
    if sem.embedding == "strict":
        return absent(q, frozenset().union(*window), sem.non_inclusion)
    return all(absent(q, s, sem.non_inclusion) for s in window)


def embeddings(itemsets: Sequence[Sequence[str]], p: Pattern, c: Constraints = FREE) -> Iterator[tuple[int, ...]]:
    """Positions of the positive itemsets, in lexicographic order."""
    sets = [frozenset(x) for x in itemsets]
    wanted = [frozenset(x) for x in p.positives]

    def go(k: int, e: tuple[int, ...]) -> Iterator[tuple[int, ...]]:
        if k == len(wanted):
            yield e
            return
        first = e[-1] + 1 if e else 1
        last = min(len(sets), e[-1] + c.maxgap) if e and c.maxgap is not None else len(sets)
        for j in range(first, last + 1):
            if wanted[k] <= sets[j - 1] and (not e or c.maxspan is None or j - e[0] <= c.maxspan):
                yield from go(k + 1, (*e, j))

    yield from go(0, ())


def first_violation(itemsets: Sequence[Sequence[str]], p: Pattern, e: tuple[int, ...], sem: Semantics) -> int | None:
    """The first gap (from 1) of an embedding that holds what it should lack."""
    sets = [frozenset(x) for x in itemsets]
    for k, q in enumerate(p.absences):
        if not window_ok(q, sets[e[k] : e[k + 1] - 1], sem):
            return k + 1
    return None


def holds(itemsets: Sequence[Sequence[str]], p: Pattern, sem: Semantics = GROWTH, c: Constraints = FREE) -> bool:
    found = False
    for e in embeddings(itemsets, p, c):
        ok = first_violation(itemsets, p, e, sem) is None
        if sem.occurrence == "soft" and ok:
            return True
        if sem.occurrence == "strict" and not ok:
            return False
        found = True
    return found and sem.occurrence == "strict"


def occurs(itemsets: Sequence[Sequence[str]], p: Pattern, sem: Semantics = GROWTH, c: Constraints = FREE) -> bool:
    """``holds`` by a fold over the pattern: states (start, position, tainted) instead of all embeddings."""
    sets = [frozenset(x) for x in itemsets]
    span, gap = c.maxspan, c.maxgap
    start = lambda j: j if span is not None else 0
    first, *rest = (frozenset(x) for x in p.positives)
    states = {(start(j), j, False) for j in range(1, len(sets) + 1) if first <= sets[j - 1]}
    for items, q in zip(rest, p.absences, strict=True):
        now = set()
        for s, i, tainted in states:
            last = len(sets) if gap is None else min(len(sets), i + gap)
            if span is not None:
                last = min(last, s + span)
            for j in range(i + 1, last + 1):
                if items <= sets[j - 1]:
                    ok = window_ok(q, sets[i : j - 1], sem)
                    if ok or sem.occurrence == "strict":
                        now.add((s, j, tainted or not ok))
        states = now
    return bool(states) and not any(t for *_, t in states)
