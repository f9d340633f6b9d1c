"""Rules between frequent patterns that start at the same vertices, in several forms that give the same rules."""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.functions.patterns import Pattern
from copath.operators.growth import Catalogue, checked, small_table
from copath.operators.matches import Matches
from copath.plans.store import cut


def sides(c: Catalogue, cfg: MinerConfig) -> list[Pattern]:
    return [p for p in c.support if len(p.hops) >= cfg.min_len]


def single_pass(matches: Matches, c: Catalogue, scale: float, cfg: MinerConfig) -> DataFrame:
    """pairs(x, y, n), x < y, by one join of the matches (pid, v, w) with themselves on the vertex; partial counts leave each task."""
    rows = matches.rows()
    a, b = rows.select("v", F.col("pid").alias("x"), "w"), rows.select("v", F.col("pid").alias("y"))
    return a.join(b, "v").where("x < y").groupBy("x", "y").agg(F.sum("w").alias("n")).where(F.col("n") / scale >= c.theta - 1e-9)


def code_pairs(lists: DataFrame) -> DataFrame:
    """(sid, a, b, n), a before or equal to b: how many vertices of a kind match both codes, from lists (sid, cids, w)."""
    one = lists.select("sid", "w", "cids", F.posexplode("cids").alias("i", "a"))
    return one.select("sid", "a", "w", F.explode(F.slice("cids", F.col("i") + 1, F.size("cids"))).alias("b")).groupBy("sid", "a", "b").agg(F.sum("w").alias("n"))


def spread(two: DataFrame, names: DataFrame, c: Catalogue, scale: float) -> DataFrame:
    """pairs(x, y, n), x < y: counts of code pairs stand for pairs of all heads of the kind. names: (sid, cid, pid)."""
    left, right = names.select("sid", F.col("cid").alias("a"), F.col("pid").alias("p")), names.select("sid", F.col("cid").alias("b"), F.col("pid").alias("q"))
    # A code meets itself under different names.
    all_pairs = two.join(left, ["sid", "a"]).join(right, ["sid", "b"]).where("a < b OR p < q")
    return all_pairs.groupBy(F.least("p", "q").alias("x"), F.greatest("p", "q").alias("y")).agg(F.sum("n").alias("n")).where(F.col("n") / scale >= c.theta - 1e-9)


def pairs_of(lists: DataFrame, names: DataFrame, c: Catalogue, scale: float) -> DataFrame:
    """pairs(x, y, n), x < y, from lists (sid, cids, w) of codes: pairs of codes are counted for each kind, and stand for pairs of all of its heads."""
    return spread(code_pairs(lists), names, c, scale)


def merged(matches: Matches, c: Catalogue, scale: float, cfg: MinerConfig) -> DataFrame:
    """The same pairs, from vertices merged by their kind and the codes that they match."""
    return pairs_of(matches.lists(), matches.of_kind(), c, scale)


def common_bits(t: pa.Table) -> pa.Table:
    """(sid, a, b, n): set bits that each two of a kind's bitmaps of one bucket have in common, times the weight of its vertices."""
    codes = t.column("cid").to_numpy()
    order = np.argsort(codes)
    codes, maps = codes[order], np.stack([np.frombuffer(m, np.uint64) for m in t.column("m").to_pylist()])[order]
    maps = maps[:, maps.any(0)]
    n = [np.bitwise_count(maps[i:] & maps[i]).sum(1, dtype=np.int64) for i in range(len(codes))]
    a, b, n = np.repeat(codes, np.arange(len(codes), 0, -1)), np.concatenate([codes[i:] for i in range(len(codes))]), np.concatenate(n)
    ok, sid, w = n > 0, t.column("sid")[0].as_py(), t.column("w")[0].as_py()
    return pa.table({"sid": pa.array(np.full(ok.sum(), sid, np.int64)), "a": a[ok], "b": b[ok], "n": n[ok] * w})


def bitmap(matches: Matches, c: Catalogue, scale: float, cfg: MinerConfig) -> DataFrame:
    """The same counts from one bitmap for each code, kind and bucket of sources, which are numbered anew so that buckets are full."""
    sources = cut(matches.sources.own.withColumn("k", F.monotonically_increasing_id()))
    rows = matches.held.join(sources, "v").select("sid", "w", "cid", F.expr("bitmap_bucket_number(k)").alias("bucket"), F.expr("bitmap_bit_position(k)").alias("at"))
    maps = rows.groupBy("sid", "w", "bucket", "cid").agg(F.expr("bitmap_construct_agg(at)").alias("m"))
    two = maps.groupBy("sid", "w", "bucket").applyInArrow(common_bits, "sid long, a int, b int, n long")
    return spread(two.groupBy("sid", "a", "b").agg(F.sum("n").alias("n")), matches.of_kind(), c, scale)


def size_of(p: Pattern, cfg: MinerConfig) -> int:
    """What falls by one from a pattern to each of its parts."""
    return p.n_items + (len(p.hops) if cfg.allow_empty else 0)


def count_asked(lists: DataFrame, keys: DataFrame) -> DataFrame:
    """(sid, a, b, n) of keys(sid, a, b), with n 0 where no list has both."""
    keys = cut(keys)
    asks = keys.groupBy("sid", "a").agg(F.collect_set("b").alias("ask"))
    hits = lists.select("sid", "w", "cids", F.explode("cids").alias("a")).join(checked(asks, asks.count()), ["sid", "a"]).select("sid", "a", "w", F.explode(F.array_intersect("cids", "ask")).alias("b"))
    n = hits.groupBy("sid", "a", "b").agg(F.sum("w").alias("n"))
    return keys.join(n, ["sid", "a", "b"], "left").select("sid", "a", "b", F.coalesce("n", F.lit(0)).alias("n"))


def lattice(matches: Matches, c: Catalogue, scale: float, cfg: MinerConfig, lists: DataFrame | None = None) -> DataFrame:
    """The same pairs from the bottom up: a pair is counted if every pair with one side one step simpler is frequent.

    Pairs are tables throughout. A round joins the last one's pairs with what their sides are parts of, counts for each pair made how many of
    its parts made it, and keeps those that all did. Pairs of a pattern with itself or with one that it dominates are nodes too,
    or pairs above them would be lost; they go at the end.
    """
    own = sides(c, cfg)
    parents = {p: [q for q in p.parents(cfg.allow_empty) if c.frequent(q) and len(q.hops) >= cfg.min_len] for p in own}
    lists = matches.lists() if lists is None else lists
    names = cut(matches.of_kind())
    over = small_table(names, [(c.ids[q], c.ids[p]) for p in own for q in parents[p]], "part int, whole int")
    need = small_table(names, [(c.ids[p], len(parents[p]), size_of(p, cfg)) for p in own], "pid int, need int, size int")
    roots = [c.ids[p] for p in own if not parents[p]]
    began = time.monotonic()
    # Pairs of patterns without parts, and every pattern with itself, by the pair's size.
    of_roots = names.join(small_table(names, [(i,) for i in roots], "pid int"), "pid", "left_semi").select("sid", "cid", "pid")
    wanted = of_roots.groupBy("sid").agg(F.collect_set("cid").alias("ask"))
    first = pairs_of(lists.join(wanted, "sid").select("sid", "w", F.array_intersect("cids", "ask").alias("cids")), of_roots, c, scale)
    seeds = first.union(small_table(names, [(c.ids[p], c.ids[p], round(c.support[p] * scale)) for p in own], "x int, y int, n long"))
    sized = seeds.join(need.select(F.col("pid").alias("x"), F.col("size").alias("sx")), "x").join(need.select(F.col("pid").alias("y"), F.col("size").alias("sy")), "y")
    seeds = cut(sized.select("x", "y", "n", (F.col("sx") + F.col("sy")).alias("total")))
    c.log("rules", 0, len(roots) * (len(roots) - 1) // 2, seeds.where("x < y").count(), began)
    sizes = [size_of(p, cfg) for p in own]
    left, right = names.select("sid", F.col("cid").alias("ca"), F.col("pid").alias("x")), names.select("sid", F.col("cid").alias("cb"), F.col("pid").alias("y"))
    counted: DataFrame | None = None
    good, out = None, [seeds.where("x < y").select("x", "y", "n")]
    for total in range(2 * min(sizes, default=1), 2 * max(sizes, default=0) + 1):
        began, here = time.monotonic(), seeds.where(F.col("total") == total).select("x", "y")
        if c.late():
            break
        if good is not None:
            one = good.join(over, good.x == over.part).select(F.col("whole").alias("a"), F.col("y").alias("b"))
            other = good.where("x < y").join(over, good.y == over.part).select(F.col("whole").alias("a"), F.col("x").alias("b"))
            made = one.union(other).where("a != b").groupBy(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y")).agg(F.count("*").alias("have"))
            wanted = made.join(need.select(F.col("pid").alias("x"), F.col("need").alias("nx")), "x").join(need.select(F.col("pid").alias("y"), F.col("need").alias("ny")), "y").where("have = nx + ny")
            cand = cut(wanted.select("x", "y"))
            generated = cand.count()
            if generated:
                # Pairs of patterns that differ in their heads ask for the same pairs of codes: each is counted once in all rounds.
                asked = cut(cand.join(left, "x").join(right, ["sid", "y"]).select("x", "y", "sid", F.least("ca", "cb").alias("a"), F.greatest("ca", "cb").alias("b")))
                keys = asked.select("sid", "a", "b").distinct()
                now = count_asked(lists, keys if counted is None else keys.join(counted, ["sid", "a", "b"], "left_anti"))
                counted = cut(now if counted is None else counted.union(now))
                found = cut(asked.join(counted, ["sid", "a", "b"]).groupBy("x", "y").agg(F.sum("n").alias("n")).where(F.col("n") / scale >= c.theta - 1e-9))
                out.append(found)
                here = here.union(found.select("x", "y"))
                c.log("rules", total, generated, found.count(), began)
        good = cut(here)
    return reduce(DataFrame.union, out).select("x", "y", "n")


#: Rows of code pairs up to which all pairs of each list are cheaper than the lattice's rounds.
PAIR_ROWS = 200_000_000


def cheapest(matches: Matches, c: Catalogue, scale: float, cfg: MinerConfig) -> DataFrame:
    """All pairs of each list of codes, or the lattice where that would be too many rows."""
    lists = matches.lists()
    rows = lists.agg(F.sum(F.size("cids") * (F.size("cids") + 1) / 2)).first()[0] or 0
    return pairs_of(lists, matches.of_kind(), c, scale) if rows <= PAIR_ROWS else lattice(matches, c, scale, cfg, lists)


FORMS = {"auto": cheapest, "single_pass": single_pass, "merged": merged, "bitmap": bitmap, "lattice": lattice}


def dominated_pairs(c: Catalogue, own: list[Pattern]) -> list[tuple[int, int]]:
    """(x, y), x < y, of patterns one of which dominates the other; found through hashing on the simpler one's first item and label."""
    by_start: dict[tuple, list[Pattern]] = {}
    for p in own:
        first = p.head[:1] or (None,)
        by_start.setdefault((first[0], p.labels[:1]), []).append(p)
        if p.hops:
            by_start.setdefault((first[0], ()), [])
    out = set()
    for p in own:
        for first in (*p.head, None):
            for start in ((first, p.labels[:1]), (first, ())):
                for q in by_start.get(start, ()):
                    if p != q and p.dominates(q):
                        out.add(tuple(sorted((c.ids[p], c.ids[q]))))
    return sorted(out)


def implied_pairs(c: Catalogue, own: list[Pattern]) -> list[tuple[int, int]]:
    """(x, y), x < y: a fixed hop beside the reach pattern of the same parts, which it implies."""
    out = []
    for p in own:
        if p.reach:
            q = Pattern(p.head, p.hops)
            if q in c.support:
                out.append(tuple(sorted((c.ids[p], c.ids[q]))))
    return out


def mine(matches: Matches, c: Catalogue, scale: float, cfg: MinerConfig) -> DataFrame:
    """pairs(x, y, n), x < y, frequent, without pairs in which one side dominates the other."""
    own = sides(c, cfg)
    began = time.monotonic()
    # The single pass joins matches as they are; the others need one code for each set of vertices.
    pairs = FORMS[cfg.rule_form](matches if cfg.rule_form == "single_pass" else matches.merged(), c, scale, cfg)
    drop = [] if cfg.keep_dominated else dominated_pairs(c, own)
    if cfg.drop_implied:
        drop += implied_pairs(c, own)
    if drop:
        pairs = pairs.join(small_table(pairs, drop, "x int, y int"), ["x", "y"], "left_anti")
    pairs = cut(pairs)
    if not any(step == "rules" for step, *_ in c.rounds):
        c.log("rules", 1, len(own) * (len(own) - 1) // 2, pairs.count(), began)
    return pairs
