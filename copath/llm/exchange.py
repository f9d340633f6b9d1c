"""Texts in parts, and compact messages between parts and hash buckets.

Rows are dealt into parts of a few megabytes by a hash of the row. Each part is one
group, so a part can gather its keys, drop repeats and send each bucket one sorted,
compressed list; a bucket answers each part with one value for each key it sent, in
order. A key held by a third of all rows arrives once from each part at most, and
rows leave a part at most as often as it has keys. Rows without an id are dealt one by one, so that
equal ones are no hot group either.
"""

from __future__ import annotations

from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from copath.llm import kernel as K
from copath.llm.store import free_name, write_table

PART_BYTES = 3 << 20
#: What a part sends to a bucket, and what a bucket answers.
MESSAGE = "bucket int, pid int, kind int, blob binary"


def parts(docs: DataFrame, id_col: str, text_col: str, *more, part_bytes: int = PART_BYTES) -> tuple[DataFrame, int]:
    """(pid, id, text, more), and the bytes of all texts. Null texts are empty; ids are whole numbers or null."""
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("text"), *more)
    size, nulls = rows.agg(F.coalesce(F.sum(F.octet_length("text") + 32), F.lit(0)), F.count_if(F.col("id").isNull())).first()
    n = F.lit(max(1, ceil(size / part_bytes)))
    if nulls:
        # The row's place tells rows without an id apart; it is written down, as a second run could count otherwise.
        place = F.when(F.col("id").isNull(), F.monotonically_increasing_id())
        return write_table(rows.withColumn("pid", F.pmod(F.xxhash64("id", "text", place), n).cast("int")))[0], size
    return rows.withColumn("pid", F.pmod(F.xxhash64("id", "text"), n).cast("int")), size


def numbered(docs: DataFrame, id_col: str) -> tuple[DataFrame, DataFrame | None]:
    """The rows with whole numbers for ids, in the order of the ids; and, if ids were something else, a table (id, num) of both."""
    if isinstance(docs.schema[id_col].dataType, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return docs, None
    own = docs.select(F.col(f"`{id_col}`").alias("id")).where("id IS NOT NULL").distinct().orderBy("id")
    table, _ = write_table(own.withColumn("num", F.monotonically_increasing_id()))
    names = table.withColumnsRenamed({"id": (old := free_name(docs, "old")), "num": (num := free_name(docs, "num"))})
    rest = [F.col(num).alias(c) if c == id_col else F.col(f"`{c}`") for c in docs.columns]
    return docs.join(names, F.col(f"`{id_col}`") == F.col(old), "left").select(*rest), table


def renamed(out: DataFrame, table: DataFrame | None, col: str) -> DataFrame:
    """Puts the ids back that ``numbered`` replaced."""
    if table is None:
        return out
    rest = [F.col("id").alias(c) if c == col else F.col(f"`{c}`") for c in out.columns]
    return out.join(table, F.col(f"`{col}`") == F.col("num"), "left").select(*rest)


def buckets_for(keys: float, each: float = 1e6) -> int:
    return max(1, min(1 << 30, ceil(keys / each)))


def tally(told: DataFrame, kind: int) -> int:
    """Sum of the counts that buckets put into messages of a kind to nobody (pid -1)."""
    return told.where((F.col("pid") == -1) & (F.col("kind") == kind)).agg(F.sum(F.conv(F.hex("blob"), 16, 10).cast("long"))).first()[0] or 0


def count_of(n: int) -> bytes:
    return np.array([n], ">i8").tobytes()


def cuts(sorted_keys: np.ndarray, bits: int, n: int) -> np.ndarray:
    """Where each bucket's keys begin, in a sorted array of ``bits``-bit keys."""
    edges = [(b << bits) // n for b in range(n)]
    return np.append(np.searchsorted(sorted_keys, np.array(edges, np.uint64)), len(sorted_keys))


def rows(pid: int, made: list[tuple[int, int, bytes]]) -> pa.Table:
    """Messages (bucket, kind, blob) of a part."""
    K.tidy()
    return pa.table(
        {
            "bucket": pa.array([m[0] for m in made], pa.int32()),
            "pid": pa.array([pid] * len(made), pa.int32()),
            "kind": pa.array([m[1] for m in made], pa.int32()),
            "blob": pa.array([m[2] for m in made], pa.binary()),
        }
    )


def answers(bucket: int, made: list[tuple[int, int, bytes]]) -> pa.Table:
    """Messages (pid, kind, blob) of a bucket."""
    K.tidy()
    return pa.table(
        {
            "bucket": pa.array([bucket] * len(made), pa.int32()),
            "pid": pa.array([m[0] for m in made], pa.int32()),
            "kind": pa.array([m[1] for m in made], pa.int32()),
            "blob": pa.array([m[2] for m in made], pa.binary()),
        }
    )


def join(blobs: list[bytes]) -> bytes:
    """Several byte strings as one."""
    return b"".join([np.array([len(blobs), *map(len, blobs)], "<i8").tobytes(), *blobs])


def split(blob: bytes) -> list[bytes]:
    n = int(np.frombuffer(blob[:8], "<i8")[0])
    ends = 8 * (n + 1) + np.cumsum(np.frombuffer(blob[8 : 8 * (n + 1)], "<i8"))
    return [blob[a:b] for a, b in zip([8 * (n + 1), *ends[:-1].tolist()], ends.tolist())]


def bits(mask: np.ndarray) -> bytes:
    return np.packbits(mask).tobytes()


def from_bits(blob: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(blob, np.uint8), count=n).view(bool)


def by_kind(table: pa.Table, kind: int) -> list[tuple[int, bytes]]:
    """(bucket, blob) of a part's answers of one kind, by bucket."""
    found = zip(table.column("bucket").to_pylist(), table.column("kind").to_pylist(), table.column("blob").to_pylist())
    return sorted((b, x) for b, k, x in found if k == kind)


# Keys that several rows share. A first round with 50-bit keys only asks which keys can
# be shared at all; it errs towards yes, and whoever asks then sends full keys for those.

SHORT = 50


def ask_shared(keys: np.ndarray, indexed: np.ndarray | None, n: int) -> tuple[np.ndarray, list[tuple[int, int, bytes]]]:
    """A part's short keys, and the messages that ask for them.

    keys: 64-bit, one for each use. indexed: uses that can be found; a key counts as shared if
    it is used twice anywhere and one of the uses can be found (None: every use).
    """
    short = keys >> K.U(64 - SHORT)
    flag = np.ones(len(keys), np.uint64) if indexed is None else indexed.astype(np.uint64)
    s = np.sort(short << K.U(1) | flag)
    k = s >> K.U(1)
    new = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1]))) if len(k) else np.zeros(0, np.int64)
    size = np.diff(np.append(new, len(k)))
    uniq = k[new]
    send = uniq << K.U(2) | (s[new + size - 1] & K.U(1)) << K.U(1) | (size > 1).astype(np.uint64)
    at = cuts(uniq, SHORT, n)
    return uniq, [(b, 0, K.pack_sorted(send[lo:hi])) for b, (lo, hi) in enumerate(zip(at[:-1].tolist(), at[1:].tolist())) if hi > lo]


def tell_shared(table: pa.Table) -> pa.Table:
    """A bucket's answer to ask_shared: one bit for each key."""
    sent = [(p, K.unpack_sorted(b)) for p, b in zip(table.column("pid").to_pylist(), table.column("blob").to_pylist())]
    s = np.sort(np.concatenate([v for _, v in sent]))
    k = s >> K.U(2)
    new = np.flatnonzero(np.concatenate(([True], k[1:] != k[:-1])))
    size = np.diff(np.append(new, len(k)))
    seen = np.bitwise_or.reduceat(s & K.U(3), new)
    shared = k[new][(seen & K.U(2) > 0) & ((size > 1) | (seen & K.U(1) > 0))]
    made = []
    if len(shared):
        for p, v in sent:
            v = v >> K.U(2)
            mask = shared[np.minimum(np.searchsorted(shared, v), len(shared) - 1)] == v
            if mask.any():
                made.append((p, 0, bits(mask)))
    return answers(table.column("bucket")[0].as_py(), made)


def shared_keys(uniq: np.ndarray, told: list[tuple[int, bytes]], n: int) -> np.ndarray:
    """The short keys that the buckets' answers say are shared, sorted."""
    at, mask = cuts(uniq, SHORT, n), np.zeros(len(uniq), bool)
    for b, x in told:
        mask[at[b] : at[b + 1]] = from_bits(x, at[b + 1] - at[b])
    return uniq[mask]


def among(keys: np.ndarray, shared: np.ndarray) -> np.ndarray:
    """Which 64-bit keys have one of the short keys."""
    if not len(shared):
        return np.zeros(len(keys), bool)
    short = keys >> K.U(64 - SHORT)
    near = np.zeros(1 << 20, bool)
    near[shared >> K.U(SHORT - 20)] = True
    out = near[short >> K.U(SHORT - 20)]
    at = np.flatnonzero(out)
    out[at] = shared[np.minimum(np.searchsorted(shared, short[at]), len(shared) - 1)] == short[at]
    return out
