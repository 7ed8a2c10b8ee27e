"""Random small databases and a search over all position combinations."""

import random
from itertools import combinations

from negseq.functions.pattern import Pattern
from negseq.functions.semantics import Constraints, Semantics


def database(rng: random.Random, names: str = "abcd", n: int = 6) -> list[list[list[str]]]:
    return [[sorted(rng.sample(names, rng.randint(1, min(3, len(names))))) for _ in range(rng.randint(2, 7))] for _ in range(n)]


def holds(itemsets, p: Pattern, sem: Semantics, c: Constraints) -> bool:
    """All combinations of positions, straight from the definitions."""
    verdicts = []
    for e in combinations(range(1, len(itemsets) + 1), len(p.positives)):
        if not all(set(x) <= set(itemsets[i - 1]) for x, i in zip(p.positives, e, strict=True)):
            continue
        if any(c.maxgap is not None and b - a > c.maxgap for a, b in zip(e, e[1:], strict=False)) or (c.maxspan is not None and e[-1] - e[0] > c.maxspan):
            continue
        ok = True
        for q, a, b in zip(p.absences, e, e[1:], strict=False):
            window = itemsets[a : b - 1]
            if not q:
                continue
            if sem.embedding == "strict":
                window = [sorted({x for s in window for x in s})]
            for s in window:
                inside = set(q) & set(s)
                if (inside if sem.non_inclusion == "total" else inside == set(q)):
                    ok = False
        verdicts.append(ok)
    return (any(verdicts) if sem.occurrence == "soft" else bool(verdicts) and all(verdicts))
