"""Path patterns: value class, canonical text, dominance; and the same tests as column expressions.

Canonical text: ``{a,b}|label|{c}``; items in byte order, a reach label ends in ``*``. In items
and labels, backslash, comma, bar and braces are escaped by a backslash.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import Column
from pyspark.sql import functions as F

SPECIAL = re.compile(r"([\\,|{}*])")


def escape(name: str) -> str:
    return SPECIAL.sub(r"\\\1", name)


@dataclass(frozen=True, order=True)
class Pattern:
    """head: items of the source; hops: (label, items) of each step. A reach pattern has one hop whose label repeats."""

    head: tuple[int, ...]
    hops: tuple[tuple[int, tuple[int, ...]], ...] = ()
    reach: bool = False

    def __len__(self) -> int:
        return len(self.hops)

    def __bool__(self) -> bool:
        return True

    @property
    def sets(self) -> tuple[tuple[int, ...], ...]:
        return (self.head, *(s for _, s in self.hops))

    @property
    def labels(self) -> tuple[tuple[int, bool], ...]:
        return tuple((label, self.reach) for label, _ in self.hops)

    @property
    def n_items(self) -> int:
        return sum(map(len, self.sets))

    @property
    def unit(self) -> bool:
        return all(len(s) == 1 for s in self.sets)

    @property
    def kind(self) -> str:
        return "reach" if self.reach else "fixed"

    def with_sets(self, sets) -> Pattern:
        return Pattern(sets[0], tuple((label, s) for (label, _), s in zip(self.hops, sets[1:])), self.reach)

    def without_one_item(self, allow_empty: bool = False):
        """Immediate generalisations by one item, at any position."""
        sets = self.sets
        for i, s in enumerate(sets):
            if len(s) > 1 or allow_empty and len(s) == 1:
                for x in s:
                    yield self.with_sets((*sets[:i], tuple(y for y in s if y != x), *sets[i + 1 :]))

    def parents(self, allow_empty: bool = False):
        """One item fewer anywhere, or the last hop gone if it asks for one item (where sets may be empty: for none)."""
        yield from self.without_one_item(allow_empty)
        if len(self.hops) > 1 and len(self.hops[-1][1]) == (0 if allow_empty else 1):
            yield Pattern(self.head, self.hops[:-1])

    def dominates(self, other: Pattern) -> bool:
        """At least as long, with the same labels on the other's length and supersets at each of its positions."""
        n = len(other.hops)
        return n <= len(self.hops) and other.labels == self.labels[:n] and all(set(b) <= set(a) for a, b in zip(self.sets, other.sets))

    def text(self, items: list[str], labels: list[str]) -> str:
        show = lambda s: "{" + ",".join(escape(items[i]) for i in s) + "}"
        return "|".join([show(self.head), *(f"{escape(labels[label])}{'*' * self.reach}|{show(s)}" for label, s in self.hops)])


def parse(text: str, items: list[str], labels: list[str]) -> Pattern:
    """The pattern of a canonical text."""
    item_id, label_id = {x: i for i, x in enumerate(items)}, {x: i for i, x in enumerate(labels)}
    parts, now, i = [], "", 0
    while i < len(text):
        if text[i] == "\\":
            now += text[i : i + 2]
            i += 2
            continue
        if text[i] == "|":
            parts.append(now)
            now = ""
        else:
            now += text[i]
        i += 1
    parts.append(now)
    plain = lambda s: re.sub(r"\\(.)", r"\1", s)
    read = lambda s: tuple(sorted(item_id[plain(x)] for x in re.findall(r"(?:\\.|[^,\\])+", s[1:-1])))
    reach = len(parts) > 1 and bool(re.search(r"(?<!\\)(?:\\\\)*\*$", parts[1]))
    name = lambda s: label_id[plain(s[:-1] if reach else s)]
    return Pattern(read(parts[0]), tuple((name(a), read(b)) for a, b in zip(parts[1::2], parts[2::2])), reach)


#: Type of a pattern as a column.
STRUCT = "struct<kind: string, head: array<int>, hops: array<struct<label: int, items: array<int>>>>"


def as_row(p: Pattern):
    return (p.kind, list(p.head), [(label, list(s)) for label, s in p.hops])


def covers(items: Column, wanted: Column) -> Column:
    """Whether an item array holds every wanted item."""
    return F.size(F.array_except(wanted, items)) == 0


def is_unit(p: Column) -> Column:
    return (F.size(p["head"]) == 1) & F.forall(p["hops"], lambda h: F.size(h["items"]) == 1)


def dominates(p: Column, q: Column) -> Column:
    """Whether pattern column p dominates pattern column q (a pattern dominates itself)."""
    n = F.size(q["hops"])
    pairs = F.zip_with(F.slice(p["hops"], 1, F.greatest(n, F.lit(1))), q["hops"], lambda a, b: b["label"].isNull() | ((a["label"] == b["label"]) & covers(a["items"], b["items"])))
    same_kind = (p["kind"] == q["kind"]) | (n == 0)
    return same_kind & (n <= F.size(p["hops"])) & covers(p["head"], q["head"]) & ((n == 0) | F.forall(pairs, lambda x: F.coalesce(x, F.lit(False))))


def subsets(items: tuple[int, ...], most: int | None = None):
    """Non-empty subsets of sorted items, smallest first."""
    for k in range(1, min(len(items), most or len(items)) + 1):
        yield from combinations(items, k)
