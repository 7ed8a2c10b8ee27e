"""The language of absence patterns, on the driver and as columns.

Text form: ``a !c (b d)`` - positive itemsets with at most one negated itemset between
two of them. An item with a blank, ``(``, ``)``, ``!`` or a back-quote is back-quoted.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKENS = "array<struct<neg: boolean, items: array<string>>>"
_PART = re.compile(r"\s*(!|\(|\)|`(?:[^`]|``)*`|[^\s()!`]+)")


class PatternError(ValueError):
    """A text or a list of elements is no absence pattern; the message says why."""


@dataclass(frozen=True)
class Element:
    neg: bool
    items: tuple[str, ...]


@dataclass(frozen=True)
class Pattern:
    elements: tuple[Element, ...]

    @property
    def text(self) -> str:
        return " ".join(("!" if e.neg else "") + (quote(e.items[0]) if len(e.items) == 1 else f"({' '.join(map(quote, e.items))})") for e in self.elements)

    @property
    def positives(self) -> tuple[tuple[str, ...], ...]:
        return tuple(e.items for e in self.elements if not e.neg)

    @property
    def absences(self) -> tuple[tuple[str, ...], ...]:
        """The negated itemset after each positive one but the last; empty for none."""
        out: list[tuple[str, ...]] = []
        for before, e in zip(self.elements, self.elements[1:], strict=False):
            if e.neg:
                out.append(e.items)
            elif not before.neg:
                out.append(())
        return tuple(out)

    @property
    def stats(self) -> dict[str, int]:
        negs = [len(e.items) for e in self.elements if e.neg]
        return {"n_items": sum(len(e.items) for e in self.elements), "n_itemsets": len(self.positives), "n_neg": len(negs), "max_neg_size": max(negs, default=0)}

    def positive_part(self) -> Pattern:
        return Pattern(tuple(e for e in self.elements if not e.neg))

    def partner(self) -> Pattern:
        """All absences turned into presences."""
        return Pattern(tuple(Element(False, e.items) for e in self.elements))

    def single_partners(self, unit: str = "itemset") -> list[Pattern]:
        """The positive part with one absence turned into a presence; unit 'item' takes each of its items alone."""
        out = []
        for k, e in enumerate(self.elements):
            for items in ([e.items] if unit == "itemset" else [(x,) for x in e.items]) if e.neg else []:
                out.append(Pattern(tuple(Element(False, items if i == k else x.items) for i, x in enumerate(self.elements) if not x.neg or i == k)))
        return out


def quote(item: str) -> str:
    return item if item and not re.search(r"[\s()!`]", item) else "`" + item.replace("`", "``") + "`"


def build(elements: list[tuple[bool, list[str] | tuple[str, ...]]]) -> Pattern:
    """A checked pattern in canonical form: items sorted and distinct, empty absences dropped."""
    out = []
    for neg, items in elements:
        if not items and neg:
            continue
        if not items:
            raise PatternError("a positive itemset is empty")
        out.append(Element(neg, tuple(sorted(set(items)))))
    if not out:
        raise PatternError("a pattern has at least one positive itemset")
    if out[0].neg or out[-1].neg:
        raise PatternError("an absence stands between two positive itemsets, not at an end")
    if any(a.neg and b.neg for a, b in zip(out, out[1:], strict=False)):
        raise PatternError("two absences stand side by side")
    return Pattern(tuple(out))


def parse(text: str) -> Pattern:
    at, elements, inside, neg = 0, [], None, False
    while text[at:].strip():
        m = _PART.match(text, at)
        if m is None:
            raise PatternError(f"not readable at {at}: {text[at:]!r}")
        at, part = m.end(), m.group(1)
        if part == "!":
            if inside is not None or neg:
                raise PatternError("an absence holds one itemset; nesting is not in the language")
            neg = True
        elif part == "(":
            if inside is not None:
                raise PatternError("itemsets do not nest; an absence of a sequence is not in the language")
            inside = []
        elif part == ")":
            if inside is None:
                raise PatternError("a bracket closes that was not opened")
            if neg and not inside:
                raise PatternError("an absence is empty")
            elements.append((neg, inside))
            inside, neg = None, False
        else:
            item = part[1:-1].replace("``", "`") if part[0] == "`" else part
            if inside is not None:
                inside.append(item)
            else:
                elements.append((neg, [item]))
                neg = False
    if inside is not None or neg:
        raise PatternError("the text ends inside an element")
    return build(elements)


def validate(text: str) -> str | None:
    """None for a pattern, else the reason why it is none."""
    try:
        parse(text)
    except PatternError as e:
        return str(e)
    return None


def precedes(p: Pattern, q: Pattern, strict: bool = False) -> bool:
    """The order along which support falls: q begins with the positive itemsets of p (the last may be larger in q), and each absence of q between them contains that of p."""
    a, b = p.positives, q.positives
    if len(a) > len(b) or any(x != y for x, y in zip(a[:-1], b, strict=False)) or not set(a[-1]) <= set(b[len(a) - 1]):
        return False
    if any(not set(x) <= set(y) for x, y in zip(p.absences, q.absences, strict=False)):
        return False
    return not (strict and p == q)


def classic_subpattern(p: Pattern, q: Pattern) -> bool:
    """Inclusion as for positive patterns, absences treated as elements of their own; support does not fall along it."""
    at = 0
    for e in p.elements:
        while at < len(q.elements) and not (q.elements[at].neg == e.neg and set(e.items) <= set(q.elements[at].items)):
            at += 1
        if at == len(q.elements):
            return False
        at += 1
    return True


# the same on columns of tokens


def quoted(item: Column) -> Column:
    return F.when(item.rlike(r"^$|[\s()!`]"), F.concat(F.lit("`"), F.replace(item, F.lit("`"), F.lit("``")), F.lit("`"))).otherwise(item)


def text_of(tokens: Column | str) -> Column:
    tokens = F.col(tokens) if isinstance(tokens, str) else tokens
    one = lambda t: F.concat(
        F.when(t["neg"], F.lit("!")).otherwise(F.lit("")),
        F.when(F.size(t["items"]) == 1, quoted(F.element_at(t["items"], 1))).otherwise(F.concat(F.lit("("), F.array_join(F.transform(t["items"], quoted), " "), F.lit(")"))),
    )
    return F.array_join(F.transform(tokens, one), " ")


def positive_part(tokens: Column | str) -> Column:
    return F.filter(tokens, lambda t: ~t["neg"])


def positive_partner(tokens: Column | str) -> Column:
    return F.transform(tokens, lambda t: F.struct(F.lit(False).alias("neg"), t["items"].alias("items")))


def stats(tokens: Column | str) -> Column:
    """n_items, n_itemsets, n_neg, max_neg_size."""
    negs = F.filter(tokens, lambda t: t["neg"])
    total = lambda xs: F.aggregate(xs, F.lit(0), lambda s, t: s + F.size(t["items"]))
    tokens = F.col(tokens) if isinstance(tokens, str) else tokens
    return F.struct(total(tokens).alias("n_items"), (F.size(tokens) - F.size(negs)).alias("n_itemsets"), F.size(negs).alias("n_neg"), F.coalesce(F.array_max(F.transform(negs, lambda t: F.size(t["items"]))), F.lit(0)).alias("max_neg_size"))


def is_pattern(tokens: Column | str) -> Column:
    """Whether tokens follow the language."""
    tokens = F.col(tokens) if isinstance(tokens, str) else tokens
    at = lambda i: F.get(tokens, i)
    filled = F.forall(tokens, lambda t: F.size(t["items"]) > 0)
    apart = ~F.exists(F.transform(tokens, lambda t, i: t["neg"] & F.coalesce(at(i + 1)["neg"], F.lit(True))), lambda x: x)
    return filled & apart & (F.size(tokens) > 0) & ~F.coalesce(at(F.lit(0))["neg"], F.lit(True))


def precedes_column(p: Column, q: Column) -> Column:
    """``precedes`` on two columns of tokens."""
    pos = lambda t: F.transform(positive_part(t), lambda e: e["items"])
    gaps = lambda t: F.transform(F.filter(F.transform(t, lambda e, i: F.struct(e["neg"].alias("neg"), F.when(F.coalesce(F.get(t, i + 1)["neg"], F.lit(False)), F.get(t, i + 1)["items"]).otherwise(F.array().cast("array<string>")).alias("after"))), lambda e: ~e["neg"]), lambda e: e["after"])
    a, b = pos(p), pos(q)
    n = F.size(a)
    front = F.forall(F.zip_with(F.slice(a, 1, n - 1), F.slice(b, 1, n - 1), lambda x, y: x == y), lambda x: x)
    last = F.size(F.array_except(F.element_at(a, -1), F.get(b, n - 1))) == 0
    absent = F.forall(F.zip_with(F.slice(gaps(p), 1, n - 1), F.slice(gaps(q), 1, n - 1), lambda x, y: F.size(F.array_except(x, y)) == 0), lambda x: x)
    return (n <= F.size(b)) & front & F.coalesce(last, F.lit(False)) & absent
