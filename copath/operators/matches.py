"""Which source matches which pattern, kept as (code, vertex) rows and the kinds of the vertices."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.operators import balance
from copath.operators.growth import Sources, bit, small_table
from copath.plans.store import cut

#: Numbers of 64 bits that a vertex's codes may take.
MASKS = 16


def marked(codes: list[tuple[int, int, int]]):
    """For batches of masks with n, h1 and h2: of each code (cid, mask, bit) that some row has, the sum of n and the hashes of its rows."""

    def f(batches):
        for t in batches:
            column = {name: t.column(name).to_numpy() for name in t.schema.names}
            out = []
            for cid, j, k in codes:
                has = (column[f"m{j}"] >> k & 1).astype(bool)
                if has.any():
                    out.append((cid, column["n"][has].sum(), *[np.bitwise_xor.reduce(column[h][has]) for h in ("h1", "h2")]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*out), (pa.int32(), *[pa.int64()] * 3))], ["cid", "n", "h1", "h2"])

    return f


@dataclass
class Matches:
    """listed(cid, v), or masks(v, sid, w, m0, m1, ...) and the mask and bit of each code, with names (head's pid, cid, pid) and sources; or, of the plain method, rows direct(pid, v, w) as they are."""

    listed: DataFrame | None = None
    sources: Sources | None = None
    names: list[tuple[int, int, int]] | None = None
    direct: DataFrame | None = None
    #: (v, part) of a placement, and the number of parts.
    plan: tuple[DataFrame, int] | None = None
    masks: DataFrame | None = None
    at: dict[int, tuple[int, int]] | None = None
    #: The different masks of each kind, if they were made before.
    alike: DataFrame | None = None

    @property
    def held(self) -> DataFrame | None:
        """(cid, v)"""
        return self.listed if self.masks is None else self.opened(self.masks, "v")

    def codes(self) -> list[int]:
        return sorted({cid for _, cid, _ in self.names})

    def opened(self, df: DataFrame, *columns: str) -> DataFrame:
        """(cid, columns) of rows with masks, for each code that is named."""
        lanes = [m for m in self.masks.columns if m not in ("v", "sid", "w")]
        bits = small_table(df, [(self.at[cid][0], bit(self.at[cid][1]), cid) for cid in self.codes()], "lane int, bit long, cid int")
        rows = df.select(*columns, F.posexplode(F.array(*lanes)).alias("lane", "mask")).where("mask != 0")
        return rows.join(bits, "lane").where("mask & bit != 0").select("cid", *columns)

    def distinct(self) -> DataFrame:
        """(sid, m0, m1, ..., w, n): the different masks of each kind, their weight and number of vertices."""
        if self.alike is not None:
            return self.alike
        by = [m for m in self.masks.columns if m not in ("v", "w")]
        return self.masks.groupBy(*by).agg(F.sum("w").alias("w"), F.count("*").alias("n"))

    def merged(self) -> Matches:
        """The same matches with one code for all that start at the same vertices (a reach beside its hop, a set beside its rarest item).

        Codes are told apart by their number of vertices and 128 bits of hashes over these, or over the different masks that have them; as many rows as codes reach the driver.
        """
        if self.direct is not None:
            return self
        alike = None
        if self.masks is None:
            rows = self.listed.select("cid", F.lit(1).cast("long").alias("n"), *[F.xxhash64("v", F.lit(seed)).alias(f"h{seed}") for seed in (1, 2)])
        else:
            alike = cut(self.distinct())
            of = [m for m in alike.columns if m not in ("w", "n")]
            hashed = alike.select(*of[1:], "n", *[F.xxhash64(*of, F.lit(seed)).alias(f"h{seed}") for seed in (1, 2)])
            rows = hashed.mapInArrow(marked([(cid, *self.at[cid]) for cid in self.codes()]), "cid int, n long, h1 long, h2 long")
        marks = rows.groupBy("cid").agg(F.sum("n").alias("n"), F.bit_xor("h1").alias("h1"), F.bit_xor("h2").alias("h2")).collect()
        first: dict[tuple, int] = {}
        of_code = {r.cid: first.setdefault((r.n, r.h1, r.h2), r.cid) for r in sorted(marks)}
        if len(first) == len(of_code):
            return replace(self, alike=alike)
        names = [(head, of_code[cid], pid) for head, cid, pid in self.names if cid in of_code]
        if self.masks is not None:
            return replace(self, alike=alike, names=names)
        kept = self.listed.join(small_table(self.listed, [(k,) for k in sorted(first.values())], "cid int"), "cid", "left_semi").select("cid", "v")
        return replace(self, listed=kept, names=names)

    @property
    def tables(self) -> list[DataFrame | None]:
        """What has to stay for the rows to be read again."""
        return [self.listed, self.masks, self.direct, *((self.sources.own, self.sources.heads) if self.sources else ())]

    def of_kind(self) -> DataFrame:
        """(sid, cid, pid): the pattern that a code is for a vertex of a kind, for each of the kind's heads."""
        heads = self.sources.heads
        return heads.join(small_table(heads, self.names, "pid int, cid int, whole int"), "pid").select("sid", "cid", F.col("whole").alias("pid"))

    def rows(self) -> DataFrame:
        """(pid, v, w)"""
        if self.direct is not None:
            return self.direct
        held = self.listed.join(self.sources.own, "v") if self.masks is None else self.opened(self.masks, "v", "sid", "w")
        return held.join(self.of_kind(), ["sid", "cid"]).select("pid", "v", "w")

    def lists(self) -> DataFrame:
        """(sid, cids, w): the different lists of codes that vertices of a kind match, and how many vertices match each. A list is no longer than the catalogue.

        The codes of a vertex are bits of a few numbers, and only different lists are opened.
        """
        codes, at = self.codes(), self.at
        if self.masks is None:
            held, by = self.listed, ["v"]
            if self.plan is not None:
                held, by = balance.place(held, *self.plan), ["part", "v"]
            if not codes or len(codes) > 64 * MASKS:
                per = held.groupBy(*by).agg(F.sort_array(F.collect_list("cid")).alias("cids"))
                return cut(per.join(self.sources.own, "v").groupBy("sid", "cids").agg(F.sum("w").alias("w")))
            at, masks = {cid: (k >> 6, k & 63) for k, cid in enumerate(codes)}, [f"m{j}" for j in range((len(codes) + 63) // 64)]
            bits = small_table(held, [(cid, j, bit(k)) for cid, (j, k) in at.items()], "cid int, block int, bit long")
            per = held.join(bits, "cid").groupBy(*by).agg(*[F.bit_or(F.when(F.col("block") == j, F.col("bit")).otherwise(0)).alias(m) for j, m in enumerate(masks)])
            lists = per.join(self.sources.own, "v").groupBy("sid", *masks).agg(F.sum("w").alias("w"))
        else:
            lists = self.distinct()
        has = [F.when(F.col(f"m{at[cid][0]}").bitwiseAND(F.lit(bit(at[cid][1]))) != 0, cid).otherwise(-1) for cid in codes]
        return cut(lists.select("sid", F.array_remove(F.array(*has), -1).alias("cids"), "w").where(F.size("cids") > 0))
