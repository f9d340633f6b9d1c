"""Benchmark decontamination: a broadcast hash set of benchmark windows meets every window of every document.

The benchmark's windows are gathered in blocks of at most ``block_bytes`` of text. One
block is the rule; each further block is one more pass that adds to the document's bitmap of hit words, so that the driver and
the workers hold one block at a time. A hit is a hash found in the set whose words then equal the item's words, byte for byte.

Null, empty and word-less texts have no words and no hits. Repeated documents are judged
one by one. Benchmark rows without words have no window; items that repeat an id
count once. An empty benchmark hits nothing.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.llm import kernel as K
from copath.llm.store import write_table

TABLE = K.word_table()
BLOCK_BYTES = 32 << 20


class WindowSet:
    """Windows of benchmark items: sorted hashes by length, items and words of each."""

    def __init__(self, ids: list[str], texts: list[str | None], n: int):
        buf, off = K.flat(pa.array(texts, pa.string()), K.ALNUM)
        start, end, first = K.words(buf, off, TABLE)
        h = K.word_hashes(buf, start, end)
        self.sizes: dict[int, tuple] = {}
        found: dict[int, dict[int, tuple[list[bytes], set[str]]]] = {}
        raw = buf.tobytes()
        for d, item in enumerate(ids):
            lo, hi = int(first[d]), int(first[d + 1])
            size = min(n, hi - lo)
            if size:
                for i, key in enumerate(K.windows(h[lo:hi], size).tolist()):
                    text = b" ".join(raw[s:e] for s, e in zip(start[lo + i : lo + i + size], end[lo + i : lo + i + size]))
                    found.setdefault(size, {}).setdefault(key, {}).setdefault(text, set()).add(item)
        for size, by in found.items():
            keys = np.array(sorted(by), np.uint64)
            near = np.zeros(1 << 22, bool)
            near[keys >> K.U(42)] = True
            self.sizes[size] = keys, near, [{t: sorted(x) for t, x in by[k].items()} for k in keys.tolist()]


def hits(buf, start, end, first, known: WindowSet) -> tuple[np.ndarray, list[set]]:
    """Which words are hit, and the items found in each text."""
    total = len(start)
    h = K.word_hashes(buf, start, end)
    hit, items = np.zeros(total, bool), [set() for _ in range(len(first) - 1)]
    for size, (keys, near, members) in known.sizes.items():
        w = K.windows(h, size)
        at = np.flatnonzero(near[w >> K.U(42)] & K.inside_text(first, size, total))
        rank = np.minimum(np.searchsorted(keys, w[at]), len(keys) - 1)
        same = keys[rank] == w[at]
        at, rank = at[same], rank[same]
        doc = np.searchsorted(first, at, "right") - 1
        good = []
        for i, r, d in zip(at.tolist(), rank.tolist(), doc.tolist()):
            text = b" ".join(buf[s:e].tobytes() for s, e in zip(start[i : i + size].tolist(), end[i : i + size].tolist()))
            if ids := members[r].get(text):
                good.append(i)
                items[d].update(ids)
        hit |= K.covered(np.array(good, np.int64), size, total)
    return hit, items


def scan(docs: DataFrame, benchmark: DataFrame, id_col="doc_id", text_col="text", item_col="item_id", item_text="text", n=10, block_bytes=BLOCK_BYTES, finish=None, finish_schema: str | None = None) -> DataFrame:
    """Per document: id, text, hit (one byte a word), items (distinct ids, sorted); or what ``finish`` makes of such batches, in the same task."""
    spark = docs.sparkSession
    bench = benchmark.select(F.coalesce(F.col(item_col).cast("string"), F.lit("")).alias("i"), F.coalesce(item_text, F.lit("")).alias("t"))
    id_type = docs.schema[id_col].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.lit(None).cast("binary").alias("hit"), F.array().cast("array<string>").alias("items"))
    size = bench.agg(F.sum(F.octet_length("t"))).first()[0] or 0
    schema = f"id {id_type}, text string, hit binary, items array<string>"
    for block, is_last in blocks_of(bench.toLocalIterator() if size > block_bytes else bench.collect(), block_bytes):
        known = spark.sparkContext.broadcast(WindowSet([i for i, _ in block], [t for _, t in block], n))

        last = finish if is_last else None

        def add(batches: Iterator[pa.RecordBatch], known=known) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for b in K.slices(whole, "text"):
                    buf, off = K.flat(b.column("text"), K.ALNUM)
                    start, end, first = K.words(buf, off, TABLE)
                    hit, items = hits(buf, start, end, first, known.value)
                    before = b.column("hit").to_pylist()
                    bits = hit.view(np.uint8)
                    maps = [bits[lo:hi].tobytes() for lo, hi in zip(first[:-1].tolist(), first[1:].tolist())]
                    maps = [m if x is None else (np.frombuffer(m, np.uint8) | np.frombuffer(x, np.uint8)).tobytes() for m, x in zip(maps, before)]
                    items = [sorted(x.union(y or ())) for x, y in zip(items, b.column("items").to_pylist())]
                    yield pa.RecordBatch.from_arrays([b.column("id"), b.column("text"), pa.array(maps, pa.binary()), pa.array(items, pa.list_(pa.string()))], ["id", "text", "hit", "items"])

        def one(batches, add=add, last=last):
            return add(batches) if last is None else last(add(batches))

        out = out.mapInArrow(one, schema if last is None else finish_schema)
        if not is_last:
            out, _ = write_table(out)
            known.destroy()
    return out


def blocks_of(rows, most: int):
    """(block, whether it is the last) of rows (i, t): up to ``most`` characters of text each, with one row at least. No rows: one empty block."""
    block, held, waiting = [], 0, None
    for r in rows:
        if waiting is not None and not block:
            yield waiting, False
            waiting = None
        block.append((r.i, r.t))
        held += len(r.t)
        if held >= most:
            waiting, block, held = block, [], 0
    if waiting is not None and block:
        yield waiting, False
        waiting = None
    yield (waiting if waiting is not None else block), True


def report(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated: one row per document."""
    id_type = docs.schema[options.get("id_col", "doc_id")].dataType.simpleString()

    def one(batches):
        for b in batches:
            maps = b.column("hit").to_pylist()
            items = b.column("items").to_pylist()
            n_hit = [m.count(1) for m in maps]
            yield pa.RecordBatch.from_arrays(
                [
                    b.column("id"),
                    pa.array([len(m) for m in maps], pa.int64()),
                    pa.array(n_hit, pa.int64()),
                    pa.array([len(x) for x in items], pa.int64()),
                    pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in items], pa.string()),
                    pa.array([x > 0 for x in n_hit], pa.bool_()),
                ],
                ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"],
            )

    return scan(docs, benchmark, **options, finish=one, finish_schema=f"doc_id {id_type}, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def clean(docs: DataFrame, benchmark: DataFrame, id_col="doc_id", text_col="text", drop_share: float = 0.5, **options) -> DataFrame:
    """The documents without the benchmark's words; those with at least ``drop_share`` of their words hit go whole.

    A run of hit words goes from its first byte to its last. Clean documents stay as they are; other columns stay.
    """
    rest = [c for c in docs.columns if c != text_col]
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in rest]).alias("row"), F.col(text_col).alias("text"))
    schema = f"id {packed.schema['row'].dataType.simpleString()}, text string"

    def one(batches):
        for t in batches:
            if t.num_rows:
                buf, off = K.flat(t.column("text"), K.ALNUM)
                start, end, _ = K.words(buf, off, TABLE)
                texts, keep, at = t.column("text").to_pylist(), [], 0
                for d, m in enumerate(t.column("hit").to_pylist()):
                    n = len(m)
                    bits = np.frombuffer(m, np.uint8)
                    k = int(bits.sum())
                    keep.append(k == 0 or k < drop_share * n)
                    if k and keep[-1]:
                        raw, edge = texts[d].encode(), np.flatnonzero(np.diff(np.concatenate(([0], bits, [0]))))
                        lo, hi = start[at : at + n] - off[d], end[at : at + n] - off[d]
                        parts, last = [], 0
                        for s, e in zip(edge[0::2].tolist(), edge[1::2].tolist()):
                            parts.append(raw[last : lo[s]])
                            last = hi[e - 1]
                        texts[d] = b"".join([*parts, raw[last:]]).decode()
                    at += n
                out = pa.RecordBatch.from_arrays([t.column("id"), pa.array(texts, pa.string())], ["id", "text"])
                yield out.filter(pa.array(keep, pa.bool_()))

    back = scan(packed, benchmark, id_col="row", text_col="text", **options, finish=one, finish_schema=schema)
    return back.select(*[F.col("text").alias(c) if c == text_col else F.col(f"id.`{c}`").alias(c) for c in docs.columns])
