"""SimHash near-duplicates: fingerprints, then all pairs within a Hamming bound by a generalised pigeonhole.

The 64 bits are grouped so that correlated bits share a partition. With m partitions
and thresholds t_i that sum to bound - m + 1, two fingerprints within the bound agree to
t_i bits in at least one partition i. A dynamic program gives the partitions unequal
thresholds by candidate counts estimated on a bounded sample of fingerprints; the
number of partitions is the one with the least estimated cost. Probes and index meet by
partition value, every pair that meets is verified on all 64 bits, and only a
spanning forest of the verified pairs leaves a task.

Null, empty and word-less texts have fingerprint zero, which links like any other.
Repeated rows share a component.

``keep_first`` links by fingerprints first and judges these links by their shingle sets; similar sets whose
fingerprints are further apart meet by rare shingles.
"""

from __future__ import annotations

from functools import reduce
from hashlib import blake2b
from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.llm import kernel as K
from copath.llm.components import components, local_roots
from copath.llm.store import Tables, free_name, write_table

TABLE = K.word_table()


def fingerprints_of(texts, shingle: int = 4, seed: int = 42) -> np.ndarray:
    """Fingerprint of each text: bit b is 1 if it is set in over half of the shingles' XXH64 values."""
    buf, off = K.flat(texts, bytes.lower)
    start, end, first = K.words(buf, off, TABLE)
    # The words, joined by one space: byte i of the result comes from a word or is its separator.
    size = end - start + 1
    to = np.concatenate(([0], np.cumsum(size)))
    src = np.arange(to[-1]) + np.repeat(start - to[:-1], size)
    joined = buf[src]
    joined[to[1:] - 1] = 32
    raw = joined.tobytes()
    count = np.diff(first)
    n_shingles = np.where(count >= shingle, count - shingle + 1, np.minimum(count, 1))
    at = np.concatenate(([0], np.cumsum(n_shingles)))
    head = np.arange(at[-1]) + np.repeat(first[:-1] - at[:-1], n_shingles)
    tail = np.minimum(head + shingle, np.repeat(first[1:], n_shingles))
    lo, hi = to[head].tolist(), (to[tail] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(raw[s:e], seed) for s, e in zip(lo, hi)), np.uint64, len(lo))
    out = np.zeros(len(count), np.uint64)
    full = np.flatnonzero(n_shingles)
    if len(full):
        ones = np.empty((len(full), 64), np.int64)
        for b in range(64):
            ones[:, b] = np.add.reduceat((h >> K.U(b)).astype(np.uint8) & 1, at[full], dtype=np.int32)
        bits = ones * 2 > n_shingles[full][:, None]
        out[full] = (bits.astype(np.uint64) << np.arange(64, dtype=np.uint64)).sum(1, dtype=np.uint64)
    return out


def fingerprints(docs: DataFrame, id_col="doc_id", text_col="text", shingle=4, seed=42) -> DataFrame:
    """(id, fp): the fingerprint as a signed 64-bit integer."""

    def one(batches):
        for whole in batches:
            for b in K.slices(whole, "text"):
                yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(fingerprints_of(b.column("text"), shingle, seed).view(np.int64))], ["id", "fp"])

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(one, f"id {docs.schema[id_col].dataType.simpleString()}, fp long")


def correlated_groups(bits: np.ndarray, m: int) -> list[list[int]]:
    """64 bit numbers in m groups of nearly equal size; a group starts at the least correlated free bit and takes the most correlated."""
    with np.errstate(all="ignore"):  # bits that never change
        c = np.abs(np.nan_to_num(np.corrcoef(bits.T))) if len(bits) > 2 else np.zeros((64, 64))
    np.fill_diagonal(c, 0)
    free, out = list(range(64)), []
    for g in range(m):
        want = len(free) // (m - g)
        group = [min(free, key=lambda b: (c[b][free].sum(), b))]
        free.remove(group[0])
        while len(group) < want:
            b = max(free, key=lambda b: (c[b][group].sum(), -b))
            group.append(b)
            free.remove(b)
        out.append(sorted(group))
    return out


#: Cost of comparing a pair, where a probe that is sent costs one.
PAIR_COST = 0.02


def plan_partitions(sample: np.ndarray, n: int, bound: int, most: int | None = None) -> list[tuple[int, int]]:
    """(bit mask, threshold) of each partition to probe, for n distinct fingerprints of which ``sample`` are some."""
    bits = (sample[:, None] >> np.arange(64, dtype=np.uint64) & K.U(1)).astype(np.uint8)
    half, n = len(sample) // 2, max(n, 1000)
    best = None
    for m in range(2, (most or bound + 1) + 1):
        groups = correlated_groups(bits, m)
        masks = [sum(1 << b for b in g) for g in groups]
        cost = []
        for g, mask in zip(groups, masks):
            near = np.bitwise_count((sample[:half, None] ^ sample[None, half : 2 * half]) & K.U(mask)) if half else np.zeros((1, 1))
            row = [0.0]
            for t in range(bound - m + 2):
                # Share of pairs within t bits here, never below what independent even bits would give.
                even = sum(comb(len(g), k) for k in range(t + 1))
                pairs = max(float((near <= t).mean()), even / 2.0 ** len(g)) * n * n / 2
                row.append(n * (even + (t > 0)) + PAIR_COST * pairs)
            cost.append(row)
        total = bound - m + 1
        # least[s]: least cost so far with thresholds that sum to s; a threshold of -1 skips a partition.
        least = {0: (0.0, ())}
        for row in cost:
            nxt: dict[int, tuple] = {}
            for s, (c, picks) in least.items():
                for t in range(-1, len(row) - 1):
                    cand = (c + row[t + 1], (*picks, t))
                    if s + t not in nxt or cand < nxt[s + t]:
                        nxt[s + t] = cand
            least = nxt
        if total in least and (best is None or least[total][0] < best[0]):
            best = least[total][0], [(k, t) for k, t in zip(masks, least[total][1]) if t >= 0]
    return best[1]


def flips(mask: int, t: int) -> list[int]:
    """All changes of up to t bits inside a mask, none first."""
    bits = [1 << b for b in range(64) if mask >> b & 1]
    return [sum(c) for k in range(t + 1) for c in combinations(bits, k)]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def group_links(part: np.ndarray, key: np.ndarray, fp: np.ndarray, own: np.ndarray, bound: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the verified pairs among rows with equal (part, key), one of which is an index row."""
    order = np.lexsort((~own, key, part))
    part, key, fp, own = part[order], key[order], fp[order], own[order]
    if not len(fp):
        return fp, fp
    new = np.concatenate(([True], (part[1:] != part[:-1]) | (key[1:] != key[:-1])))
    begin = np.flatnonzero(new)
    size = np.diff(np.append(begin, len(fp)))
    indexed = np.add.reduceat(own.astype(np.int64), begin)
    nodes, which = np.unique(fp, return_inverse=True)
    root = np.arange(len(nodes))
    wide = 256

    def merge(p: np.ndarray, q: np.ndarray) -> None:
        """Joins the components of nodes p[i] and q[i]; only pairs that still differ are kept in hand."""
        nonlocal root
        p, q = root[p], root[q]
        live = p != q
        if live.any():
            root = local_roots(len(nodes), np.concatenate((np.arange(len(nodes)), p[live])), np.concatenate((root, q[live])))

    live = np.repeat((size > 1) & (size <= wide) & (indexed > 0), size)
    gid = np.cumsum(new)
    rows = np.flatnonzero(live & own)
    shift = 1
    while len(rows):
        rows = rows[rows + shift < len(fp)]
        rows = rows[gid[rows] == gid[rows + shift]]
        ok = rows[np.bitwise_count(fp[rows] ^ fp[rows + shift]) <= bound]
        merge(which[ok], which[ok + shift])
        shift += 1
    for g in np.flatnonzero((size > wide) & (indexed > 0)):
        lo, k, n = begin[g], indexed[g], size[g]
        for i in range(lo, lo + k, 256):
            left = slice(i, min(i + 256, lo + k))
            for j in range(i, lo + n, 2048):
                right = slice(j, min(j + 2048, lo + n))
                apart = root[which[left]][:, None] != root[which[right]][None]
                r, c = np.nonzero(apart & (np.bitwise_count(fp[left, None] ^ fp[None, right]) <= bound))
                merge(which[left][r], which[right][c])
    linked = np.flatnonzero(root != np.arange(len(nodes)))
    return nodes[linked], nodes[root[linked]]


def block_links(own: np.ndarray, fp: np.ndarray, bound: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the verified pairs of an index row and any row."""
    nodes, which = np.unique(np.concatenate((own, fp)), return_inverse=True)
    p, q = which[: len(own)], which[len(own) :]
    root = np.arange(len(nodes))
    for i in range(0, len(own), 256):
        for j in range(0, len(fp), 2048):
            apart = root[p[i : i + 256]][:, None] != root[q[j : j + 2048]][None]
            r, c = np.nonzero(apart & (np.bitwise_count(own[i : i + 256, None] ^ fp[None, j : j + 2048]) <= bound))
            if len(r):
                root = local_roots(len(nodes), np.concatenate((np.arange(len(nodes)), p[i + r])), np.concatenate((root, q[j + c])))
    linked = np.flatnonzero(root != np.arange(len(nodes)))
    return nodes[linked], nodes[root[linked]]


#: Rows that a task holds at once; a group of more is compared block by block, by many tasks.
HELD = 1 << 16


def whole_groups(batches, keys: list[str], most: int = HELD):
    """(table, dense) of a stream that is sorted by ``keys``: whole groups, about ``most`` rows at a time; the rows of a group of more, in pieces, as dense."""
    held, dense_key = [], None

    def first_row(t):
        return tuple(t.column(c)[0].as_py() for c in keys)

    def starts(t):
        """Where each group begins."""
        new = np.zeros(t.num_rows, bool)
        new[0] = True
        for c in keys:
            x = t.column(c).to_numpy()
            new[1:] |= x[1:] != x[:-1]
        return np.flatnonzero(new)

    for b in batches:
        if not b.num_rows:
            continue
        held.append(b)
        if sum(x.num_rows for x in held) < most:
            continue
        t = pa.Table.from_batches(held)
        at = starts(t)
        if dense_key is not None and first_row(t) == dense_key:
            end = int(at[1]) if len(at) > 1 else t.num_rows
            yield t.slice(0, end), True
            t, at = t.slice(end), at[1:] - end
        if len(at) > 1:
            yield t.slice(0, int(at[-1])), False
            t = t.slice(int(at[-1]))
        if t.num_rows >= most:
            dense_key = first_row(t)
            yield t, True
            t = t.slice(t.num_rows)
        held = t.to_batches()
    if held:
        t = pa.Table.from_batches(held)
        if t.num_rows and dense_key is not None and first_row(t) == dense_key:
            at = starts(t)
            end = int(at[1]) if len(at) > 1 else t.num_rows
            yield t.slice(0, end), True
            t = t.slice(end)
        if t.num_rows:
            yield t, False


def dense_links(rows: DataFrame, bound: int) -> DataFrame:
    """Links (a, b) among rows (part, key, fp, own) of groups too large for a task: index blocks against all blocks of their group."""
    sizes = rows.groupBy("part", "key").agg(F.ceil(F.count_if("own") / HELD).alias("owns"), F.ceil(F.count("*") / HELD).alias("all")).where("owns > 0")
    placed = rows.join(sizes, ["part", "key"])
    place = lambda n: F.pmod(F.xxhash64("fp"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), (F.col(n) - 1).cast("int")))
    left = placed.where("own").select("part", "key", "fp", F.lit(True).alias("own"), place("owns").alias("i"), every("all").alias("j"))
    right = placed.select("part", "key", "fp", F.lit(False).alias("own"), every("owns").alias("i"), place("all").alias("j"))

    def compare(t: pa.Table) -> pa.Table:
        own, fp = t.column("own").to_numpy().astype(bool), t.column("fp").to_numpy().view(np.uint64)
        a, b = block_links(fp[own], fp[~own], bound)
        return pa.table({"a": a.view(np.int64), "b": b.view(np.int64)})

    return left.unionByName(right).groupBy("part", "key", "i", "j").applyInArrow(compare, "a long, b long")


def link_fingerprints(fps: DataFrame, bound: int = 4, sample_rows: int = 4096) -> DataFrame:
    """Links (a, b) whose components are those of all pairs of distinct ``fp`` values within ``bound`` bits.

    Thresholds are fitted on at most ``sample_rows`` fingerprints; every fingerprint is indexed and probed.
    """
    distinct, _ = write_table(fps.select("fp").distinct())
    n = distinct.count()
    rate = min(1.0, 1.2 * sample_rows / max(n, 1))
    sample = np.array([r.fp for r in distinct.sample(rate, 7).limit(sample_rows).collect()], np.int64).view(np.uint64)
    plan = plan_partitions(sample, n, bound)
    spec = [(i, signed(mask), signed(f)) for i, (mask, t) in enumerate(plan) for f in flips(mask, t)]
    probes = F.explode(F.expr("array(" + ",".join(f"named_struct('p',{p},'m',{m}L,'f',{f}L)" for p, m, f in spec).replace("-9223372036854775808L", "(-9223372036854775807L-1L)") + ")"))
    keyed = distinct.select("fp", probes.alias("x")).select(F.col("x.p").alias("part"), F.col("fp").bitwiseAND(F.col("x.m")).bitwiseXOR(F.col("x.f")).alias("key"), "fp", (F.col("x.f") == 0).alias("own"))

    def one(batches):
        for t, dense in whole_groups(batches, ["part", "key"]):
            col = lambda c: t.column(c).to_numpy()  # noqa: E731, B023
            if dense:
                none = pa.nulls(t.num_rows, pa.int64())
                out = [none, none, t.column("part").combine_chunks(), t.column("key").combine_chunks(), t.column("fp").combine_chunks(), t.column("own").combine_chunks()]
            else:
                a, b = group_links(col("part"), col("key"), col("fp").view(np.uint64), col("own").astype(bool), bound)
                out = [pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.nulls(len(a), pa.int32()), pa.nulls(len(a), pa.int64()), pa.nulls(len(a), pa.int64()), pa.nulls(len(a), pa.bool_())]
            yield pa.RecordBatch.from_arrays(out, ["a", "b", "part", "key", "fp", "own"])

    found, _ = write_table(keyed.repartition("part", "key").sortWithinPartitions("part", "key").mapInArrow(one, "a long, b long, part int, key long, fp long, own boolean"))
    links, dense = found.where("part IS NULL").select("a", "b"), found.where("part IS NOT NULL").select("part", "key", "fp", "own")
    return links if dense.isEmpty() else links.union(dense_links(dense, bound))


def group_fingerprints(fps: DataFrame, bound: int = 4) -> DataFrame:
    """(id, fp, component_id) of a stored table (id, fp): the smallest id that links reach, the row's own included."""
    roots = components(link_fingerprints(fps, bound))
    of_fp = fps.groupBy("fp").agg(F.min("id").alias("first")).join(roots, F.col("fp") == F.col("node"), "left")
    of_fp = of_fp.select("fp", "first", F.coalesce("root", "fp").alias("root"))
    smallest = of_fp.groupBy("root").agg(F.min("first").alias("component_id"))
    labels = of_fp.join(smallest, "root").select("fp", "component_id")
    return fps.join(labels, "fp").select("id", "fp", "component_id")


def near_duplicates(docs: DataFrame, id_col="doc_id", text_col="text", shingle=4, bound=4) -> DataFrame:
    """(id, fp, component_id) of every document."""
    fps, _ = write_table(fingerprints(docs, id_col, text_col, shingle))
    return group_fingerprints(fps, bound)


def shingle_sets(texts, shingle: int) -> list[np.ndarray]:
    """Sorted distinct hashes of each text's word shingles (fewer words: the whole sequence; none: no shingle)."""
    buf, off = K.flat(texts, bytes.lower)
    start, end, first = K.words(buf, off, TABLE)
    h = K.word_hashes(buf, start, end)
    w = K.windows(h, shingle)
    out = []
    for lo, hi in zip(first[:-1].tolist(), first[1:].tolist()):
        n = hi - lo
        out.append(np.unique(w[lo : hi - shingle + 1]) if n >= shingle else K.windows(h[lo:hi], n) if n else w[:0])
    return out


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    """Jaccard similarity of two sets; two empty sets are equal."""
    if not len(a) and not len(b):
        return 1.0
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


#: Tables of ids up to this many rows are broadcast; larger ones are joined by a shuffle.
BROADCAST_IDS = 2_000_000


def checked(ids: DataFrame) -> DataFrame:
    """A stored table, to be broadcast if it is small enough."""
    return F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids


#: Slots that shingles are counted in. The counts only order shingles; any order finds the same pairs.
SLOTS = 1 << 16


def set_digests(texts: DataFrame, shingle: int) -> DataFrame:
    """(id, digest): equal digests, equal shingle sets."""

    def one(batches):
        for whole in batches:
            for b in K.slices(whole, "text"):
                yield pa.RecordBatch.from_arrays([b.column("id"), pa.array([blake2b(x.tobytes(), digest_size=16).digest() for x in shingle_sets(b.column("text"), shingle)], pa.binary())], ["id", "digest"])

    return texts.mapInArrow(one, f"id {texts.schema['id'].dataType.simpleString()}, digest binary")


def slot_counts(texts: DataFrame, shingle: int) -> np.ndarray:
    """How many shingles of all texts fall into each slot."""

    def one(batches):
        n = np.zeros(SLOTS, np.int64)
        for whole in batches:
            for b in K.slices(whole, "text"):
                n += np.bincount((np.concatenate(shingle_sets(b.column("text"), shingle)) >> K.U(48)).astype(np.int64), minlength=SLOTS)
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(n[at])], ["slot", "n"])

    t = texts.mapInArrow(one, "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(SLOTS, np.int64)
    out[t.column("slot").to_numpy()] = t.column("n").to_numpy()
    return out


def shared_prefixes(texts: DataFrame, shingle: int, least: float) -> DataFrame:
    """(key, id, n, pos): of each text's n shingles, rare ones first, those that two texts with similarity ``least`` can't both lack.

    Two such sets share at least ``least`` of either one's shingles, so that the first one they share is among the first
    n - least * n + 1 of both. Keys that one text alone has are left out.
    """
    counts = texts.sparkSession.sparkContext.broadcast(slot_counts(texts, shingle))
    kind = f"key long, id {texts.schema['id'].dataType.simpleString()}, n int, pos int"

    def first(batches):
        for whole in batches:
            for b in K.slices(whole, "text"):
                sets = shingle_sets(b.column("text"), shingle)
                size = np.array([len(x) for x in sets], np.int64)
                take = np.where(size > 0, size - np.ceil(least * size - 1e-9).astype(np.int64) + 1, 0)
                h = np.concatenate(sets)
                of = np.repeat(np.arange(len(sets)), size)
                order = np.lexsort((h, counts.value[(h >> K.U(48)).astype(np.int64)], of))
                pos = np.arange(len(h)) - np.repeat(np.cumsum(size) - size, size)
                ok = pos < take[of]
                yield pa.RecordBatch.from_arrays([pa.array(h[order][ok].view(np.int64)), b.column("id").take(pa.array(of[ok])), pa.array(size[of[ok]], pa.int32()), pa.array(pos[ok], pa.int32())], ["key", "id", "n", "pos"])

    def several(batches):
        # Sorted by key: a row has company if a neighbour has its key. The last row waits for the next batch.
        last, wanted = None, False
        for b in batches:
            if not b.num_rows:
                continue
            t = pa.Table.from_batches([b] if last is None else [last, b])
            key = t.column("key").to_numpy()
            same = key[1:] == key[:-1]
            keep = np.concatenate((same, [False])) | np.concatenate(([wanted], same))
            t = t.combine_chunks()
            yield from t.slice(0, len(key) - 1).filter(pa.array(keep[:-1])).to_batches()
            last, wanted = t.slice(len(key) - 1).to_batches()[0], bool(keep[-1])
        if wanted:
            yield last

    return texts.mapInArrow(first, kind).repartition("key").sortWithinPartitions("key").mapInArrow(several, kind)


def meet(keys: np.ndarray, n: np.ndarray, pos: np.ndarray, heads: int, least: float, old: int = 0, most: int = 1 << 20):
    """Row numbers (a, b) of rows sorted by key that share a key, a among its first ``heads`` rows and before b, if they can be similar. The first ``old`` rows have met each other."""
    if not len(keys):
        return
    new = np.concatenate(([True], keys[1:] != keys[:-1]))
    begin = np.flatnonzero(new)[np.cumsum(new) - 1]
    partners = np.minimum(np.arange(len(keys)) - begin, heads)
    partners[:old] = 0
    done = np.concatenate(([0], np.cumsum(partners)))
    lo = 0
    while lo < len(keys):
        hi = max(lo + 1, int(np.searchsorted(done, done[lo] + most, "right")) - 1)
        b = np.repeat(np.arange(lo, hi), partners[lo:hi])
        a = begin[b] + np.arange(len(b)) - (done[b] - done[lo])
        need = least / (1 + least) * (n[a] + n[b]) - 1e-9
        # Shingles that both can share if this is the first one they do.
        ok = np.minimum(n[a] - pos[a], n[b] - pos[b]) >= need
        yield a[ok], b[ok]
        lo = hi


def candidates(prefixes: DataFrame, heads: int, least: float) -> DataFrame:
    """(a, b), a < b: documents with a common key, a among the ``heads`` smallest ids of the key; (null, b) if b isn't among them itself."""
    kind = prefixes.schema["id"].dataType.simpleString()

    def one(batches):
        # Sorted by key and id: of the key that a batch ends in, the first rows go on to the next batch.
        front = None
        for batch in batches:
            if not batch.num_rows:
                continue
            old = front.num_rows if front is not None else 0
            t = pa.Table.from_batches([batch] if front is None else [*front.to_batches(), batch]).combine_chunks()
            codes = t.column("id").combine_chunks().dictionary_encode()
            of, ids = codes.indices.to_numpy().astype(np.int64), codes.dictionary
            key = t.column("key").to_numpy()
            for a, b in meet(key, t.column("n").to_numpy().astype(np.int64), t.column("pos").to_numpy().astype(np.int64), heads, least, old):
                pair = np.unique(of[a] * len(ids) + of[b])
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(pair // len(ids))), ids.take(pa.array(pair % len(ids)))], ["a", "b"])
            new = np.concatenate(([True], key[1:] != key[:-1]))
            place = np.arange(len(key)) - np.flatnonzero(new)[np.cumsum(new) - 1]
            late = np.unique(of[(place >= heads) & (np.arange(len(key)) >= old)])
            yield pa.RecordBatch.from_arrays([pa.nulls(len(late), ids.type), ids.take(pa.array(late))], ["a", "b"])
            start = len(key) - 1 - int(place[-1])
            front = t.slice(start, min(heads, len(key) - start))

    return prefixes.repartition("key").sortWithinPartitions("key", "id").mapInArrow(one, f"a {kind}, b {kind}").distinct()


def similar(pairs: DataFrame, heads: DataFrame, texts: DataFrame, shingle: int, least: float) -> DataFrame:
    """The pairs (a, b) of a stored table whose texts' shingles have a Jaccard similarity of ``least`` or more; heads: a stored table of the a's."""
    kind = pairs.schema["a"].dataType.simpleString()

    def judge(batches):
        for whole in batches:
            for b in K.slices(whole, "text", 1 << 20):
                both = zip(shingle_sets(b.column("text"), shingle), shingle_sets(b.column("head"), shingle))
                yield b.select(["a", "b"]).filter(pa.array([similarity(x, y) >= least for x, y in both], pa.bool_()))

    members = texts.withColumnsRenamed({"id": "b"}).join(checked(pairs), "b")
    # One head may have any number of members: its row is the only one on its side, so a skewed join can be cut into many tasks.
    firsts = texts.withColumnsRenamed({"id": "a", "text": "head"}).join(checked(heads), "a", "left_semi")
    return members.join(firsts, "a").select("a", "b", "text", "head").mapInArrow(judge, f"a {kind}, b {kind}")


def settle(links: DataFrame) -> DataFrame:
    """(id) of the documents that go by all links (a, b), a < b: those with a linked a that stays."""
    kind = links.schema["a"].dataType.simpleString()

    def one(batches):
        # A component is in one task, by b: whatever links to b from below is settled before.
        gone = set()
        for batch in batches:
            out = []
            for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist()):
                if b not in gone and a not in gone:
                    gone.add(b)
                    out.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(out, batch.schema.field("b").type)], ["id"])

    roots = components(links)
    return links.join(roots, F.col("b") == F.col("node")).select("a", "b", "root").repartition("root").sortWithinPartitions("b").mapInArrow(one, f"id {kind}")


def fingerprint_pairs(texts: DataFrame, shingle: int, bound: int = 4) -> DataFrame:
    """(a, b), a < b: each text of texts(id, text) with the smallest id that links of fingerprints reach from it; one row for each b at most."""
    return near_duplicates(texts, "id", "text", shingle, bound).where("id != component_id").select(F.col("component_id").alias("a"), F.col("id").alias("b"))


def keep_first(docs: DataFrame, id_col="doc_id", text_col="text", shingle=5, least=0.8, bound=4) -> DataFrame:
    """The documents without those that are near-duplicates of one that stays.

    In the order of ids, a document goes if the Jaccard similarity of its shingles with those of a document that stays is
    ``least`` or more. Of equal shingle sets the smallest id goes on. Others meet the first of their fingerprints' component
    (``bound`` bits a link); sets that are similar with fingerprints further apart meet by rare shingles, and no similar pair can
    fail to. There, first each shingle's smallest id meets the rest, then more and more of those that aren't
    settled, until every pair has met or left: large groups of copies cost a row a copy and not one a pair.
    Of rows that repeat an id one stays; rows without an id all stay.
    """
    held = Tables(docs.sparkSession)
    own = F.col(id_col).isNotNull()
    if not docs.where(own).groupBy(id_col).count().where("count > 1").isEmpty():
        docs, _ = write_table(docs.where(own).dropDuplicates([id_col]).union(docs.where(~own)))
    texts = docs.where(own).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    digests = held.write(set_digests(texts, shingle))
    smallest = held.write(digests.groupBy("digest").agg(F.min("id").alias("first"), F.count("*").alias("k")).where("k > 1").select("digest", "first"))
    copies = held.write(digests.join(checked(smallest), "digest").where("id != first").select("id"))
    lost = [copies]
    different = texts.join(checked(copies), "id", "left_anti")
    linked = held.write(fingerprint_pairs(different, shingle, bound))
    known = held.write(similar(linked, held.write(linked.select("a").distinct()), texts, shingle, least))
    left = held.write(shared_prefixes(different, shingle, least))
    heads = 1
    while True:
        met = held.write(candidates(left, heads, least))
        # Pairs that fingerprints linked are judged already.
        pairs, late = held.write(met.where("a IS NOT NULL").join(checked(linked), ["a", "b"], "left_anti")), met.where("a IS NULL").select(F.col("b").alias("id"))
        links = held.write(similar(pairs, held.write(pairs.select("a").distinct()), texts, shingle, least).union(known.select("a", "b")))
        if late.isEmpty():
            break
        # Has met all smaller ids and none is similar: stays.
        stays = held.write(left.select("id").distinct().join(late, "id", "left_anti").join(links.select(F.col("b").alias("id")), "id", "left_anti"))
        goes = held.write(links.join(stays.select(F.col("id").alias("a")), "a", "left_semi").select(F.col("b").alias("id")).distinct())
        lost.append(goes)
        known = held.write(known.join(checked(goes).withColumnRenamed("id", "a"), "a", "left_anti").join(checked(goes).withColumnRenamed("id", "b"), "b", "left_anti"))
        left = held.write(left.join(checked(stays), "id", "left_anti").join(checked(goes), "id", "left_anti"))
        heads *= 8
    lost.append(settle(links))
    name = free_name(docs, "gone")
    gone, _ = write_table(reduce(DataFrame.union, lost).select(F.col("id").alias(name)))
    held.drop()
    return docs.join(checked(gone), F.col(id_col) == F.col(name), "left_anti")
