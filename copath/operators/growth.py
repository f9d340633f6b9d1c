"""Frequent patterns, level by level: item sets, fixed patterns, reach patterns.

A pattern is a head and a *code*, its hops. Codes are evaluated backwards, from their ends to the vertices that start
them, without heads and without the pairs of vertices that a walk joins: rows (code, vertex) are at most codes times vertices. Heads come in only where
rows are counted: vertices of one kind (the same items) are one group, so that a round counts (kind, code), and
supports of all heads, of one item or many, are sums over kinds. Catalogues of frequent patterns are small and live on the driver; vertices
never do. Where a prefix may be followed by any label and item that passes the bounds, candidates come from the data and
only frequent ones are named; larger sets are candidates if some head has all of their parts.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.functions.patterns import Pattern
from copath.operators.bounds import Targets, Walks
from copath.operators.kinds import ANY, Kinds
from copath.plans.store import cut

#: Candidate tables up to this many rows are broadcast.
BROADCAST_ROWS = 2_000_000


@dataclass
class Catalogue:
    """Frequent patterns with their numbers and supports, and one log row for each round."""

    theta: float
    ids: dict[Pattern, int] = field(default_factory=dict)
    names: list[Pattern] = field(default_factory=list)
    support: dict[Pattern, float] = field(default_factory=dict)
    rounds: list[tuple] = field(default_factory=list)
    late: Callable[[], bool] = lambda: False
    finished: bool = True

    def number(self, p: Pattern) -> int:
        if p not in self.ids:
            self.ids[p] = len(self.names)
            self.names.append(p)
        return self.ids[p]

    def add(self, p: Pattern, n: float) -> int:
        self.support[p] = n
        return self.number(p)

    def frequent(self, p: Pattern) -> bool:
        return p in self.support

    def of(self, length: int, reach: bool = False) -> list[Pattern]:
        return [p for p in self.support if p.reach == reach and len(p.hops) == length]

    def log(self, step: str, i: int, generated: int, frequent: int, began: float) -> None:
        self.rounds.append((step, i, generated, frequent, time.monotonic() - began))


_ARROW = {"int": pa.int32(), "long": pa.int64()}


def small_table(df: DataFrame, rows: list[tuple], schema: str) -> DataFrame:
    """Driver-side rows of whole numbers as a table; broadcast up to a checked number of rows."""
    spark, fields = df.sparkSession, [f.split() for f in schema.split(", ")]
    if not rows:
        return F.broadcast(spark.createDataFrame([], schema))
    columns = list(zip(*rows))
    table = spark.createDataFrame(pa.table({name: pa.array(columns[i], _ARROW[kind]) for i, (name, kind) in enumerate(fields)}))
    return F.broadcast(table) if len(rows) <= BROADCAST_ROWS else table


def checked(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def frequent_keys(c: Catalogue, found: DataFrame, keys: list[str], scale: float, distinct: bool = False) -> list:
    """Rows of keys and n, their estimated support, of keys whose sources (src, w) are enough. ``distinct``: a source may repeat."""
    rows = found.select(*keys, "src", "w").distinct() if distinct else found
    got = rows.groupBy(*keys).agg(F.sum("w").alias("n")).where(F.col("n") / scale >= c.theta - 1e-9).collect()
    return [(*r[:-1], r.n / scale if scale != 1 else r.n) for r in got]


def only(df: DataFrame, ids, name: str = "pid") -> DataFrame:
    ids = list(ids)
    return df.join(small_table(df, [(i,) for i in ids], f"{name} int"), name, "left_semi") if ids else df.limit(0)


def bit(k: int) -> int:
    """Bit k of a block of 64, as a signed number."""
    return (1 << (k & 63)) - ((k & 63) == 63) * (1 << 64)


#: Rows of codes at the ends of edges up to which they are broadcast to the edges.
BROADCAST_AT = 250_000


@dataclass
class Packed:
    """df(v, extra, block, mask): the codes of each vertex, 64 in a mask, so that an edge brings one row for each block and not one for each code."""

    df: DataFrame
    codes: list[int]
    name: str
    extra: tuple[str, ...] = ()
    #: What of the opened rows counts.
    only: Callable[[DataFrame], DataFrame] = lambda df: df

    def named(self, df: DataFrame, kept: list[tuple[int, ...]], name: str) -> DataFrame:
        """Rows of a table with blocks and masks, one for each code of kept(extra, code, number), with its number."""
        bits = [(*x, k >> 6, bit(k), n) for *x, k, n in kept]
        return df.join(small_table(df, bits, ", ".join([*[f"{x} int" for x in self.extra], "block int", "bit long", f"{name} int"])), [*self.extra, "block"]).where("mask & bit != 0")

    def rows(self, codes: list[int] | None = None) -> DataFrame:
        """(code, extra, v) of some codes, or all."""
        bits = [(k >> 6, bit(k), k) for k in (self.codes if codes is None else codes)]
        opened = self.df.join(small_table(self.df, bits, f"block int, bit long, {self.name} int"), "block").where("mask & bit != 0").select(self.name, *self.extra, "v")
        return self.only(opened).select(self.name, *self.extra, "v")


def packed(df: DataFrame, keys: list[str], code: str) -> DataFrame:
    """(keys, block, mask) of rows (keys, code)."""
    bits = df.select(*keys, F.shiftright(code, 6).alias("block"), F.expr(f"shiftleft(1L, {code} & 63)").alias("bit"))
    return bits.groupBy(*keys, "block").agg(F.bit_or("bit").alias("mask"))


def before(edges: DataFrame, at: DataFrame, keys: list[str], codes, name: str, extra: tuple[str, ...] = ()) -> Packed:
    """The codes of vertices whose edges lead to at(keys, extra, block, mask)."""
    got = edges.join(at, keys).groupBy(F.col("src").alias("v"), *extra, "block").agg(F.bit_or("mask").alias("mask"))
    return Packed(cut(got), sorted(set(codes)), name, extra)


def union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.union, frames)


def end_set(item: int) -> tuple[int, ...]:
    return () if item == ANY else (item,)


def frequent_itemsets(attrs: DataFrame, weights: DataFrame, c: Catalogue, scale: float, cfg: MinerConfig, n_items: int) -> DataFrame:
    """Level-wise join and prune over attrs(v, item). (pid, v, w) of all frequent item sets."""
    began = time.monotonic()
    attrs = attrs.join(weights, "v").select(F.col("v").alias("src"), "item", "w")
    rows = frequent_keys(c, attrs, ["item"], scale)
    pids = [(item, c.add(Pattern(end_set(item)), n)) for item, n in sorted(rows)]
    c.log("itemsets", 1, n_items, len(pids), began)
    level = attrs.join(small_table(attrs, pids, "item int, pid int"), "item").select("pid", "src", "w")
    frames, size = [level], 1
    attrs = attrs.where(F.col("item") != ANY)
    while pids and (cfg.max_items is None or size < cfg.max_items) and not c.late():
        began, size = time.monotonic(), size + 1
        heads = sorted(p.head for p in c.of(0) if len(p.head) == size - 1)
        known = set(heads)
        by_prefix: dict[tuple, list[int]] = {}
        for h in heads:
            by_prefix.setdefault(h[:-1], []).append(h[-1])
        cand = []
        for prefix, lasts in by_prefix.items():
            for a, b in combinations(lasts, 2):
                s = (*prefix, a, b)
                if cfg.policy == "prefix_only" or all(t in known for t in combinations(s, size - 1)):
                    cand.append((c.ids[Pattern((*prefix, a))], b, c.number(Pattern(s))))
        if not cand:
            break
        found = level.join(small_table(level, cand, "pid int, item int, new int"), "pid").join(attrs.select("src", "item"), ["src", "item"])
        found = cut(found.select(F.col("new").alias("pid"), "src", "w"))
        pids = frequent_keys(c, found, ["pid"], scale)
        for k, n in pids:
            c.add(c.names[k], n)
        c.log("itemsets", size, len(cand), len(pids), began)
        level = only(found, [k for k, _ in pids])
        frames.append(level)
    return cut(union(frames).withColumnRenamed("src", "v"))


class Ends:
    """Labels and items that may follow a prefix by the bounds, for patterns of one length."""

    def __init__(self, t: Targets, i: int, paths: Walks):
        self.t, self.i, self.after = t, i, paths.after
        self.by_label: dict[int, list[int]] = {}
        for label, item in sorted(t.ends):
            if paths.enough(i - 1, label, t.ends[label, item], t.theta):
                self.by_label.setdefault(label, []).append(item)
        self.known: dict = {}

    def before(self, p: Pattern) -> tuple[int, ...]:
        """What the bounds look at: the labels of the prefix, if degrees are counted by label."""
        return tuple(label for label, _ in p.hops) if self.t.by_label is not None else ()

    def items(self, before: tuple[int, ...], label: int) -> list[int]:
        if (before, label) not in self.known:
            own = before if self.t.by_label is not None else None
            self.known[before, label] = [x for x in self.by_label[label] if self.t.tail_ok(self.i, label, x, own)]
        return self.known[before, label]

    def labels(self, p: Pattern) -> list[int]:
        """Labels that the prefix's last set and label may be followed by, and that have an end."""
        last = p.hops[-1][0] if p.hops else None
        before, key = self.before(p), (self.before(p), last, p.sets[-1], "labels")
        if key not in self.known:
            own = before if self.t.by_label is not None else None
            after = self.by_label if last is None else self.after.get(last, ())
            self.known[key] = [label for label in self.by_label if label in after and self.items(before, label) and all(self.t.step_ok(self.i, x, label, own) for x in p.sets[-1] or (ANY,))]
        return self.known[key]


@dataclass
class Sources:
    """own(v, sid, w): the sources with their kind and weight; heads(sid, pid): the frequent item sets of each kind."""

    own: DataFrame
    heads: DataFrame


class Codes:
    """Hops of patterns, as patterns without a head: their numbers, the heads that each is frequent with, and rows (cid, v).

    Item sets that the same kinds among a label's ends have ask for the same vertices, so that codes that differ only in such sets share number
    and rows; so do a reach code and its hop where no edge of the label follows another.
    """

    def __init__(self, c: Catalogue, sources: Sources, scale: float, cfg: MinerConfig, kinds: Kinds, paths: Walks | None = None):
        self.c, self.sources, self.scale, self.cfg, self.kinds, self.paths = c, sources, scale, cfg, kinds, paths
        #: Number of a label's ends that have an item set, by kinds; codes by those.
        self.same: dict[tuple[int, tuple[int, ...]], int] = {}
        self.marks: dict[tuple, int] = {}
        self.done: dict[tuple, Pattern] = {}
        self.ids: dict[Pattern, int] = {}
        self.heads: dict[Pattern, set[int]] = {}
        #: Rows (cid, v), or codes in masks with those that are kept.
        self.frames: list[DataFrame | tuple[Packed, list[tuple]]] = []
        #: Codes of one hop that were counted, frequent or not.
        self.tried: set[Pattern] = set()

    def number(self, q: Pattern) -> int:
        return self.ids.setdefault(q, len(self.ids))

    def count(self, found: DataFrame | Packed, keys: list[str], code_of) -> list[tuple]:
        """Supports of all heads with the codes of found(keys, v); gives the keys of codes that are frequent with any head, with the code's number."""
        c = self.c
        if isinstance(found, Packed):
            # Vertices meet their kind before masks are opened.
            held = Packed(found.df.join(self.sources.own, "v"), found.codes, found.name, ("sid", "w", *found.extra), found.only).rows()
        else:
            held = found.join(self.sources.own, "v")
        by_kind = held.groupBy("sid", *keys).agg(F.sum("w").alias("n"))
        rows = by_kind.join(self.sources.heads, "sid").groupBy("pid", *keys).agg(F.sum("n").alias("n")).where(F.col("n") / self.scale >= c.theta - 1e-9).collect()
        out = {}
        for r in sorted(rows):
            h, key, n = c.names[r[0]], tuple(r[1:-1]), r.n / self.scale if self.scale != 1 else r.n
            q = code_of(*key)
            c.add(Pattern(h.head, q.hops, q.reach), n)
            self.heads.setdefault(q, set()).add(r[0])
            out[key] = self.number(q)
        return [(*key, cid) for key, cid in out.items()]

    def keep(self, found: DataFrame | Packed, keys: list[str], kept: list[tuple]) -> None:
        """Rows of the frequent codes."""
        if isinstance(found, Packed):
            self.frames.append((found, kept))
            return
        table = small_table(found, kept, ", ".join(f"{k} int" for k in (*keys, "cid")))
        self.frames.append(found.join(table, keys).select("cid", "v"))

    def key(self, q: Pattern) -> tuple:
        return (q.reach and not self.one_hop(q), *((label, self.same[label, s]) for label, s in q.hops))

    def one_hop(self, q: Pattern) -> bool:
        return self.paths.hops(q.hops[0][0], self.cfg.hops) == 1

    def learn(self, codes) -> None:
        """Which sets of these codes the same kinds of a label's ends have, by the number of kinds and 128 bits of hashes over these."""
        hops = sorted({hop for q in codes for hop in q.hops} - self.same.keys())
        if hops:
            sets = {s: k for k, s in enumerate(sorted({s for _, s in hops}))}
            asked = small_table(self.kinds.attrs, [(sets[s], label, k) for k, (label, s) in enumerate(hops)], "hid int, label int, hop int")
            held = self.kinds.holding([(k, s) for s, k in sets.items()], "hid").join(asked, "hid").join(self.kinds.ends.select("label", "sid"), ["label", "sid"])
            got = {r.hop: (r.n, r.h1, r.h2) for r in held.groupBy("hop").agg(F.count("*").alias("n"), *[F.bit_xor(F.xxhash64("sid", F.lit(k))).alias(f"h{k}") for k in (1, 2)]).collect()}
            self.same |= {hop: self.marks.setdefault(got.get(k, (0, 0, 0)), len(self.marks)) for k, hop in enumerate(hops)}

    def alike(self, cand) -> tuple[dict[tuple, list[Pattern]], list[Pattern]]:
        """Candidates by key, and one of each key that no frequent code has and some kinds hold."""
        self.learn((*self.heads, *cand))
        for q in self.heads:
            self.done.setdefault(self.key(q), q)
        groups: dict[tuple, list[Pattern]] = {}
        for q in sorted(cand, key=lambda q: q.hops):
            groups.setdefault(self.key(q), []).append(q)
        # No kind has such a set, and so no vertex; or a reach code's hop was counted and is not frequent.
        none = self.marks.get((0, 0, 0))
        fresh = [qs[0] for k, qs in groups.items() if k not in self.done and all(x != none for _, x in k[1:])]
        return groups, [q for q in fresh if not (q.reach and self.one_hop(q) and Pattern((), q.hops) in self.tried)]

    def copy(self, groups: dict[tuple, list[Pattern]]) -> int:
        """Gives candidates the heads and supports of a frequent code of their key; the number of those that have one."""
        n = 0
        for k, qs in groups.items():
            p = self.done.get(k, qs[0])
            if p not in self.heads:
                continue
            n += len(qs)
            for q in qs:
                if q != p:
                    self.ids[q], self.heads[q] = self.ids[p], set(self.heads[p])
                    for h in sorted(self.heads[p]):
                        head = self.c.names[h].head
                        self.c.add(Pattern(head, q.hops, q.reach), self.c.support[Pattern(head, p.hops, p.reach)])
        return n

    def shared(self, q: Pattern) -> set[int]:
        """Heads that all parts of a code are frequent with."""
        parts = [self.heads.get(p, set()) for p in q.without_one_item(self.cfg.allow_empty)]
        return set.intersection(*parts) if parts else set()

    def rows(self) -> DataFrame | None:
        """(cid, v) of the sources."""
        frames = [f if isinstance(f, DataFrame) else f[0].named(f[0].df, f[1], "cid").select("cid", "v") for f in self.frames]
        return cut(union(frames).join(self.sources.own.select("v"), "v", "left_semi").select("cid", "v")) if frames else None

    def masks(self, most: int) -> tuple[DataFrame, dict[int, tuple[int, int]]] | None:
        """(v, sid, w, m0, m1, ...) of the sources with a code, and the mask and bit of each code: masks stay as they were counted, and no code is opened.

        None where there are no codes, or more masks than ``most``.
        """
        lanes, at, parts, listed = {}, {}, [], []
        for i, f in enumerate(self.frames):
            if isinstance(f, DataFrame):
                listed.append(f)
                continue
            found, keep = f[0], {}
            for *x, k, cid in f[1]:
                key = (*x, k >> 6)
                if cid in at:
                    return None
                at[cid] = (lanes.setdefault((i, *key), len(lanes)), k & 63)
                keep[key] = keep.get(key, 0) | bit(k)
            table = small_table(found.df, [(*key, lanes[i, *key], m) for key, m in keep.items()], ", ".join([*[f"{x} int" for x in found.extra], "block int, lane int, keep long"]))
            parts.append(found.df.join(table, [*found.extra, "block"]).select("v", "lane", F.col("mask").bitwiseAND(F.col("keep")).alias("mask")).where("mask != 0"))
        if listed:
            rest = sorted({self.ids[q] for q in self.heads} - at.keys())
            at |= {cid: (lanes.setdefault((len(self.frames), k >> 6), len(lanes)), k & 63) for k, cid in enumerate(rest)}
            rows = union(listed)
            parts.append(rows.join(small_table(rows, [(cid, at[cid][0], bit(at[cid][1])) for cid in rest], "cid int, lane int, mask long"), "cid").select("v", "lane", "mask"))
        if not lanes or len(lanes) > most:
            return None
        per = union(parts).groupBy("v").agg(*[F.bit_or(F.when(F.col("lane") == j, F.col("mask")).otherwise(0)).alias(f"m{j}") for j in range(len(lanes))])
        return cut(per.join(self.sources.own, "v").select("v", "sid", "w", *[f"m{j}" for j in range(len(lanes))])), at

    def patterns(self) -> list[tuple[int, int, int]]:
        """(head's pid, cid, pid) of every frequent pattern with a hop."""
        c = self.c
        return [(h, self.ids[q], c.ids[Pattern(c.names[h].head, q.hops, q.reach)]) for q, heads in self.heads.items() for h in heads]


def ends_of(kinds: Kinds, edges: DataFrame, tips: dict[tuple[int, tuple[int, ...]], int], name: str = "eid") -> Packed:
    """(eid, v): vertices with an edge of the label to one that has the items; tips: (label, items) -> eid."""
    held = kinds.holding([(k, s) for (_, s), k in tips.items()], "eid")
    label_of = small_table(edges, [(k, label) for (label, _), k in tips.items()], "eid int, label int")
    return before(edges, kinds.small(packed(held.join(label_of, "eid"), ["label", "sid"], "eid")), ["label", "sid"], tips.values(), name)


def at_ends(kinds: Kinds, edges: DataFrame, rows: DataFrame, extra: tuple[str, ...], codes, name: str) -> Packed:
    """The codes one hop before rows(v, label, extra, code): edges of a label into v."""
    at = cut(packed(rows, ["v", "label", *extra], name).withColumnRenamed("v", "dst"))
    return before(edges, F.broadcast(at) if at.count() <= BROADCAST_AT else at, ["dst", "label"], codes, name, extra)


def back(kinds: Kinds, edges: DataFrame, rows: DataFrame, steps: list[tuple[int, tuple[int, ...], int, int]], extra: tuple[str, ...], name: str = "suffix") -> Packed:
    """Codes (new suffix, extra) one hop before rows(suffix, extra, v): steps are (label, items, suffix, new suffix)."""
    sets = {s: k for k, s in enumerate(sorted({s for _, s, _, _ in steps}))}
    table = small_table(rows, [(sets[s], suffix, label, new) for label, s, suffix, new in steps], "hid int, suffix int, label int, new int")
    # The kind of a vertex tells which items a walk may ask for there.
    held = rows.join(kinds.own, "v").join(kinds.small(kinds.holding([(k, s) for s, k in sets.items()], "hid")), "sid")
    return at_ends(kinds, edges, held.join(table, ["hid", "suffix"]).select("v", "label", *extra, F.col("new").alias(name)), extra, [new for *_, new in steps], name)


def explicit(kinds: Kinds, edges: DataFrame, codes: list[tuple[int, Pattern]]) -> Packed:
    """(cid, v) of listed codes of one length."""
    length = len(codes[0][1].hops)
    number: list[dict] = [{q.hops: cid for cid, q in codes}] + [{} for _ in range(length - 1)]
    for j in range(1, length):
        for _, q in codes:
            number[j].setdefault(q.hops[j:], len(number[j]))
    found = ends_of(kinds, edges, {hops[0]: k for hops, k in number[-1].items()}, "suffix" if length > 1 else "cid")
    for j in range(length - 2, -1, -1):
        steps = [(hops[0][0], hops[0][1], number[j + 1][hops[1:]], k) for hops, k in number[j].items()]
        found = back(kinds, edges, found.rows(), steps, (), "suffix" if j else "cid")
    return found


def grow_fixed(kinds: Kinds, edges: DataFrame, t: Targets, paths: Walks, codes: Codes, tips: dict, first: Packed) -> None:
    """All frequent fixed patterns of length 1 to max_len. first: (eid, v) of the single ends ``tips`` that any length or reach pattern may have."""
    c, cfg = codes.c, codes.cfg
    for i in range(1, cfg.max_len + 1):
        began, ends = time.monotonic(), Ends(t, i, paths)
        # Prefixes by code; the bounds and heads are those of patterns.
        prefixes = c.of(i - 1)
        if not prefixes or not ends.by_label or c.late():
            break
        single = sorted({Pattern((), p.hops) for p in prefixes if all(len(s) <= 1 for _, s in p.hops)}, key=lambda p: p.hops)
        generated = sum(len(ends.items(ends.before(p), label)) for p in prefixes for label in ends.labels(p))
        if i == 1:
            wanted = sorted({(label, x) for p in prefixes for label in ends.labels(p) for x in ends.items((), label)})
            found = Packed(first.df, [tips[label, end_set(x)] for label, x in wanted], "eid")
            codes.tried |= {Pattern((), ((label, end_set(x)),)) for label, x in wanted}
            keys, name = ["eid"], {k: Pattern((), (hop,)) for hop, k in tips.items()}
            code_of = name.__getitem__
        else:
            found, code_of = followed(kinds, edges, ends, single, tips, first)
            keys = ["eid", "suffix"]
        kept = codes.count(found, keys, code_of)
        c.log(f"fixed_{i}", 1, generated, len(kept), began)
        if not kept:
            break
        codes.keep(found, keys, kept)
        m = 2
        while not c.late() and m <= max(q.n_items for q in (*codes.heads, *(Pattern((), p.hops) for p in prefixes))) + 1:
            began = time.monotonic()
            cand = {q: codes.shared(q) for q in (*wider_ends(codes, i, m), *longer(codes, ends, prefixes, m)) if q not in codes.heads}
            if i > 1:
                cand = {q: heads & codes.heads.get(Pattern((), q.hops[:-1]), set()) for q, heads in cand.items()}
            cand = {q: heads for q, heads in cand.items() if heads}
            if cand:
                groups, fresh = codes.alike(cand)
                codes.tried |= cand.keys() if i == 1 else set()
                if fresh:
                    names = {codes.number(q): q for q in fresh}
                    found = explicit(kinds, edges, list(names.items()))
                    kept = codes.count(found, ["cid"], names.__getitem__)
                    if kept:
                        codes.keep(found, ["cid"], kept)
                c.log(f"fixed_{i}", m, sum(map(len, cand.values())), codes.copy(groups), began)
            m += 1


def followed(kinds: Kinds, edges: DataFrame, ends: Ends, prefixes: list[Pattern], tips: dict, first: Packed) -> tuple[Packed, Callable]:
    """(eid, suffix, v): prefixes of single items with one more hop to a single item that the bounds admit, by data; and the code of (eid, suffix)."""
    length = len(prefixes[0].hops)
    number = [{} for _ in range(length)] + [{(): 0}]
    for j in range(length):
        for p in prefixes:
            number[j].setdefault(p.hops[j:], len(number[j]))
    label_of = {k: label for (label, _), k in tips.items()}
    groups: dict[tuple, int] = {}
    allowed, admitted = [], set()
    for p in prefixes:
        grp = groups.setdefault(ends.before(p), len(groups))
        for label in ends.labels(p):
            allowed.append((number[0][p.hops], label, grp))
    for before, grp in groups.items():
        admitted |= {(grp, label, tips[label, end_set(x)]) for label in ends.by_label for x in ends.items(before, label) if (label, end_set(x)) in tips}
    # Which ends may follow which last set: before any hop is taken.
    last = {}
    for p in prefixes:
        last.setdefault(p.hops[-1][1], set()).update(ends.labels(p))
    eids = sorted({k for *_, k in admitted})
    # Ends that an edge of a prefix's last label leads to, with that label.
    into = kinds.ins.where(F.col("label").isin(sorted({p.hops[-1][0] for p in prefixes}))).select("v", F.col("label").alias("by")).join(kinds.own, "v")
    rows = Packed(first.df.join(into, "v"), first.codes, "eid", ("by", "sid")).rows(eids)
    rows = rows.join(small_table(rows, [(k, label_of[k]) for k in eids], "eid int, label int"), "eid")
    sets = {s: k for k, s in enumerate(sorted(last))}
    may = small_table(rows, [(sets[s], label) for s, labels in last.items() for label in labels], "hid int, label int")
    step = small_table(rows, [(sets[hops[0][1]], hops[0][0], k) for hops, k in number[length - 1].items()], "hid int, by int, suffix int")
    held = rows.join(kinds.small(kinds.holding([(k, s) for s, k in sets.items()], "hid")), "sid").join(may, ["hid", "label"]).join(step, ["hid", "by"])
    found = at_ends(kinds, edges, held.select("v", F.col("by").alias("label"), "eid", "suffix"), ("eid",), number[length - 1].values(), "suffix")
    for j in range(length - 2, -1, -1):
        steps = [(hops[0][0], hops[0][1], number[j + 1][hops[1:]], k) for hops, k in number[j].items()]
        found = back(kinds, edges, found.rows(), steps, ("eid",))
    by_label = small_table(rows, [(k, label_of[k]) for k in eids], "eid int, label int")
    may, ends_may = small_table(rows, allowed, "suffix int, label int, grp int"), small_table(rows, [(grp, k) for grp, _, k in sorted(admitted)], "grp int, eid int")
    found.only = lambda df: df.join(by_label, "eid").join(may, ["suffix", "label"]).join(ends_may, ["grp", "eid"], "left_semi")
    names, hop_of = {k: hops for hops, k in number[0].items()}, {k: hop for hop, k in tips.items()}
    return found, lambda eid, suffix: Pattern((), (*names[suffix], hop_of[eid]))


def wider_ends(codes: Codes, i: int, m: int) -> list[Pattern]:
    """Codes of length i and m items: one more item at the end, larger than those there."""
    level = [q for q in codes.heads if not q.reach and len(q.hops) == i]
    singles: dict[tuple, list[int]] = {}
    for q in level:
        if len(q.hops[-1][1]) == 1:
            singles.setdefault((q.hops[:-1], q.hops[-1][0]), []).append(q.hops[-1][1][0])
    out = []
    for q in level:
        label, s = q.hops[-1]
        if q.n_items == m - 1 and s and (codes.cfg.max_items is None or len(s) < codes.cfg.max_items):
            out += [Pattern((), (*q.hops[:-1], (label, (*s, x)))) for x in singles.get((q.hops[:-1], label), ()) if x > s[-1]]
    return out


def longer(codes: Codes, ends: Ends, prefixes: list[Pattern], m: int) -> list[Pattern]:
    """Codes of m items: prefixes that hold a larger set somewhere, with the single ends that one of their parts has."""
    wide = {Pattern((), p.hops) for p in prefixes if any(len(s) > 1 for _, s in p.hops)}
    follow: dict[Pattern, set] = {}
    for q in codes.heads:
        if not q.reach and q.hops and len(q.hops[-1][1]) <= 1:
            follow.setdefault(Pattern((), q.hops[:-1]), set()).add(q.hops[-1])
    out = []
    for p in wide:
        if p.n_items in (m - 1, m):
            parts = [follow.get(q, set()) for q in p.without_one_item(codes.cfg.allow_empty)]
            labels, before = set(ends.labels(p)), ends.before(p)
            out += [q for hop in sorted(set.intersection(*parts)) if hop[0] in labels and (hop[1][0] if hop[1] else ANY) in ends.items(before, hop[0]) and (q := Pattern((), (*p.hops, hop))).n_items == m]
    return out


def propagate(edges: DataFrame, seeds: DataFrame, hops: int) -> DataFrame:
    """(tid, v) reached backwards from seeds(tid, label, v) in 1 to ``hops`` edges of the seed's label (0: until nothing is new)."""
    first = seeds.join(edges.select(F.col("dst").alias("v"), "label", "src"), ["v", "label"]).select("tid", "label", F.col("src").alias("v")).distinct()
    return onward(edges, cut(first), hops)


def onward(edges: DataFrame, first: DataFrame, hops: int) -> DataFrame:
    """(tid, v) of a stored table (tid, label, v), and what reaches that in ``hops`` - 1 more edges of the label (0: until nothing is new)."""
    step, first = edges.select(F.col("dst").alias("v"), "label", "src"), first.select("tid", "label", "v")
    seen, front, k = first, first, 1
    while not hops or k < hops:
        k += 1
        new = front.join(step, ["v", "label"]).select("tid", "label", F.col("src").alias("v")).distinct()
        front = cut(new.join(seen, ["tid", "label", "v"], "left_anti"))
        if k != hops and front.isEmpty():
            break
        seen = seen.union(front)
    return seen.select("tid", "v")


def wider_tails(known: set[Pattern], size: int) -> list[Pattern]:
    """Reach codes with a tail of a size, all of whose parts are frequent."""
    by_prefix: dict[tuple, list[int]] = {}
    for q in known:
        label, s = q.hops[0]
        if len(s) == size - 1 and s:
            by_prefix.setdefault((label, s[:-1]), []).append(s[-1])
    return [Pattern((), ((label, (*prefix, a, b)),), True) for (label, prefix), lasts in sorted(by_prefix.items()) for a, b in combinations(sorted(lasts), 2)]


def grow_reach(kinds: Kinds, edges: DataFrame, t: Targets, paths: Walks, codes: Codes, tips: dict, first: Packed) -> None:
    """All frequent reach patterns: single tails first, then larger ones that some head has all parts of."""
    c, cfg, hops, began = codes.c, codes.cfg, codes.cfg.hops, time.monotonic()
    name = {k: Pattern((), (hop,), True) for hop, k in tips.items()}
    labels = {label for item, label in t.starts if t.step_ok(1, item, label)}
    tails = [tips[label, end_set(x)] for label, x in paths.reach_ends(t, hops) if label in labels]
    if not tails or c.late():
        return
    groups, fresh = codes.alike([name[k] for k in tails])
    if fresh:
        few = {tips[q.hops[0]]: q.hops[0][0] for q in fresh}
        reached = onward(edges, cut(first.rows(list(few)).join(small_table(edges, list(few.items()), "eid int, label int"), "eid").withColumnRenamed("eid", "tid")), hops)
        new = codes.count(reached, ["tid"], name.__getitem__)
        if new:
            codes.keep(reached, ["tid"], new)
    kept = codes.copy(groups)
    starts = sum(t.step_ok(1, x, label) for p in c.of(0) if len(p.head) <= 1 for x in p.head or (ANY,) for label in [name[k].hops[0][0] for k in tails])
    c.log("reach", 1, starts, kept, began)
    size = 1
    while kept:
        size += 1
        if c.late() or cfg.max_items is not None and size > cfg.max_items:
            break
        began = time.monotonic()
        cand = {q: codes.shared(q) for q in wider_tails({q for q in codes.heads if q.reach}, size)}
        cand = {q: heads for q, heads in cand.items() if heads}
        if not cand:
            break
        groups, fresh = codes.alike(cand)
        if fresh:
            own = {q.hops[0]: k for k, q in enumerate(fresh)}
            label_of = small_table(edges, [(k, label) for (label, _), k in own.items()], "tid int, label int")
            reached = onward(edges, cut(ends_of(kinds, edges, own, "tid").rows().join(label_of, "tid")), hops)
            new = codes.count(reached, ["tid"], fresh.__getitem__)
            if new:
                codes.keep(reached, ["tid"], new)
        kept = codes.copy(groups)
        c.log("reach", size, sum(map(len, cand.values())), kept, began)
