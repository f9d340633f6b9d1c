"""Embedding near-duplicates: spherical k-means cells, blocked cosine products, one representative a group.

Vectors are compared only within a label (and number of components). Equal vectors become one weighted class
first. Centroids are fitted for each large label on a bounded sample; each class belongs to the cell of
its nearest centroid, and is a guest in every further cell that can hold a vector within
the angle of the threshold: one whose bisector with its own cell is no farther than that angle.
Owners of a cell meet its owners and guests, so no link is lost to a cell's edge. Cells are cut into
blocks, each pair of which is one matrix product in double precision; a block sends counts, and a
spanning forest of its links.

Vectors with a null label, null or empty or zero ones, and those with null or non-finite components link
with nothing and are their own component; so do rows without an id, whose component has none either. Repeated rows link with each
other; rows that share an id and a component are all kept if that id is the smallest. Ids are whole numbers.

Cells grow in number with the label, as far as the bounded sample can tell them apart; beyond that, and where vectors don't
cluster, a cell's work is quadratic in its rows, in blocks that many tasks share.
"""

from __future__ import annotations

from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.llm.components import components, local_roots
from copath.llm.store import free_name, write_table

#: Bytes of vectors in a block; a cell's rows are copied once for each block that they meet.
BLOCK_BYTES = 4 << 20


def unit(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def spherical_kmeans(x: np.ndarray, k: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """k unit centroids of unit vectors; an empty cell takes the vector that fits its own cell least."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=False)]
    for _ in range(rounds):
        sim = x @ c.T
        own = sim.argmax(1)
        total = np.zeros_like(c)
        np.add.at(total, own, x)
        norm = np.sqrt((total * total).sum(1))
        empty = np.flatnonzero(norm < 1e-12)
        if len(empty):
            total[empty] = x[np.argsort(sim[np.arange(len(x)), own])[: len(empty)]]
            norm = np.sqrt((total * total).sum(1))
        new = total / norm[:, None]
        if np.abs(new - c).max() < 1e-9:
            break
        c = new
    return c


def matrix(column) -> np.ndarray:
    """Rows of an Arrow list column whose lists have one length."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    n = len(column)
    return column.flatten().to_numpy(zero_copy_only=False).reshape(n, -1) if n else np.zeros((0, 1))


def groups(vectors: DataFrame, id_col="vec_id", vec_col="embedding", label_col="label", least: float = 0.93, cell_rows: int = 4096, sample_rows: int = 20_000) -> DataFrame:
    """vec_id, n_links, component_id, kept of every vector."""
    spark = vectors.sparkSession
    rows = vectors.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{vec_col}`").alias("vec"), F.col(f"`{label_col}`").alias("label"))
    good = F.expr("id IS NOT NULL AND label IS NOT NULL AND vec IS NOT NULL AND size(vec) > 0 AND NOT exists(vec, x -> x IS NULL OR isnan(x) OR abs(x) = double('inf')) AND exists(vec, x -> x != 0)")
    rows = rows.withColumn("good", F.coalesce(good, F.lit(False)))
    classes, _ = write_table(rows.where("good").groupBy("label", "vec").agg(F.min("id").alias("rep"), F.count("*").alias("w")).withColumn("dim", F.size("vec")))
    sizes = classes.groupBy("label", "dim").count()
    n = classes.count()
    large = sizes.where(F.col("count") > cell_rows)
    # Labels too small for cells of their own need no centroid; the others share the sample by their size.
    share = min(1.0, sample_rows / max(1, n))
    centroids: dict[tuple, np.ndarray] = {}
    drawn = F.pmod(F.xxhash64("vec", F.lit(3)), F.lit(1 << 30)) < int(share * (1 << 30))
    sample = classes.join(large, ["label", "dim"]).select("label", "dim", "count", "vec", "rep").where(drawn).orderBy("rep").limit(sample_rows).toArrow()
    if sample.num_rows:
        frame = sample.select(["label", "dim", "count"]).to_pandas()
        for (label, dim, count), at in frame.groupby(["label", "dim", "count"]).indices.items():
            k = min(ceil(count / cell_rows), len(at) // 20)
            if k > 1:
                centroids[label, int(dim)] = spherical_kmeans(unit(matrix(sample.column("vec").take(pa.array(at)))), k)
    known = spark.sparkContext.broadcast(centroids)
    reach = float(np.sqrt(1 - least * least)) + 1e-9 if least > 0 else 2.0

    def assign(batches):
        for b in batches:
            labels, dims = b.column("label").to_pylist(), b.column("dim").to_numpy()
            cell, owner, source = [], [], []
            by: dict[tuple, list[int]] = {}
            for i, key in enumerate(zip(labels, dims.tolist())):
                by.setdefault(key, []).append(i)
            # Many cells: a slice of rows at a time, so that their products stay small.
            for key, at in ((k, v[i : i + 2048]) for k, v in by.items() for i in range(0, len(v), 2048)):
                at = np.array(at)
                c = known.value.get(key)
                if c is None:
                    cell.append(np.zeros(len(at), np.int64))
                    owner.append(np.ones(len(at), bool))
                    source.append(at)
                    continue
                x = unit(matrix(b.column("vec").take(pa.array(at))))
                sim = x @ c.T
                own = sim.argmax(1)
                apart = np.sqrt(((c[:, None] - c[None]) ** 2).sum(2)) + 1e-300
                gap = (sim[np.arange(len(at)), own][:, None] - sim) / apart[own]
                r, cc = np.nonzero((gap <= reach) | (apart[own] < 1e-12) | (np.arange(len(c))[None] == own[:, None]))
                cell.append(cc)
                owner.append(own[r] == cc)
                source.append(at[r])
            take = pa.array(np.concatenate(source))
            yield pa.RecordBatch.from_arrays(
                [b.column("label").take(take), b.column("dim").take(take), pa.array(np.concatenate(cell), pa.int32()), pa.array(np.concatenate(owner)), b.column("rep").take(take), b.column("w").take(take), b.column("vec").take(take)],
                ["label", "dim", "cell", "own", "rep", "w", "vec"],
            )

    kind = {f.name: f.dataType.simpleString() for f in classes.schema}
    cells = classes.select("label", "dim", "rep", "w", "vec").mapInArrow(assign, f"label {kind['label']}, dim int, cell int, own boolean, rep {kind['rep']}, w long, vec {kind['vec']}")
    cells, _ = write_table(cells)
    block = F.greatest(F.lit(64), F.floor(BLOCK_BYTES / 8 / F.col("dim")))
    counts = cells.groupBy("label", "dim", "cell").agg(F.ceil(F.count_if("own") / block).alias("owns"), F.ceil(F.count("*") / block).alias("all"))
    cells = cells.join(counts, ["label", "dim", "cell"]).where("owns > 0")
    place = lambda n: F.pmod(F.xxhash64("rep"), F.col(n)).cast("int")
    other = lambda n: F.explode(F.sequence(F.lit(0), (F.col(n) - 1).cast("int")))
    fields = ["label", "dim", "cell", "rep", "w", "vec"]
    left = cells.where("own").select(*fields, F.lit(True).alias("own"), place("owns").alias("i"), other("all").alias("j"))
    right = cells.select(*fields, F.lit(False).alias("own"), other("owns").alias("i"), place("all").alias("j"))

    def compare(table: pa.Table) -> pa.Table:
        own = table.column("own").to_numpy().astype(bool)
        at, to = np.flatnonzero(own), np.flatnonzero(~own)
        reps, w = table.column("rep").to_numpy(), table.column("w").to_numpy()
        if not len(at) or not len(to):
            return pa.table({"rep": pa.array([], pa.int64()), "n": pa.array([], pa.int64()), "root": pa.array([], pa.int64())})
        x = unit(matrix(table.column("vec")))
        nodes, which = np.unique(reps, return_inverse=True)
        root, links = np.arange(len(nodes)), np.zeros(len(nodes), np.int64)
        for lo in range(0, len(at), 512):
            a = at[lo : lo + 512]
            near = (x[a] @ x[to].T >= least) & (reps[a][:, None] != reps[to][None])
            np.add.at(links, which[a], near @ w[to])
            r, c = np.nonzero(near)
            p, q = root[which[a[r]]], root[which[to[c]]]
            moved = p != q
            if moved.any():
                root = local_roots(len(nodes), np.concatenate((np.arange(len(nodes)), p[moved])), np.concatenate((root, q[moved])))
        told = np.flatnonzero((links > 0) | (root != np.arange(len(nodes))))
        return pa.table({"rep": pa.array(nodes[told], pa.int64()), "n": pa.array(links[told], pa.int64()), "root": pa.array(nodes[root[told]], pa.int64())})

    found, _ = write_table(left.unionByName(right).groupBy("label", "dim", "cell", "i", "j").applyInArrow(compare, "rep long, n long, root long"))
    links = found.groupBy("rep").agg(F.sum("n").alias("n"))
    roots = components(found, "rep", "root")
    of_class = classes.join(links, "rep", "left").join(roots, F.col("rep") == F.col("node"), "left")
    of_class = of_class.select("label", "vec", (F.coalesce("n", F.lit(0)) + F.col("w") - 1).alias("n_links"), F.coalesce("root", "rep").alias("component_id"))
    hashed = lambda d: d.withColumn("h", F.xxhash64("label", "vec"))
    judged = hashed(rows.where("good")).join(hashed(of_class), ["h", "label", "vec"]).select("id", "n_links", "component_id")
    alone = rows.where("NOT good").select("id", F.lit(0).cast("long").alias("n_links"), F.col("id").alias("component_id"))
    out = judged.unionByName(alone)
    return out.select(F.col("id").alias("vec_id"), F.col("n_links").cast("long").alias("n_links"), F.col("component_id").cast("long").alias("component_id"), F.expr("id <=> component_id").alias("kept"))


def keep_representatives(vectors: DataFrame, id_col="vec_id", **options) -> DataFrame:
    """The vectors that are their group's representative."""
    name = free_name(vectors, "keep")
    kept = groups(vectors, id_col, **options).where("kept").select(F.col("vec_id").alias(name)).distinct()
    return vectors.join(kept, F.col(f"`{id_col}`").eqNullSafe(F.col(name)), "left_semi")
