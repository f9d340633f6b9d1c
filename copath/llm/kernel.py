"""Vectorised text kernels that the operators share: words, word hashes, windows, compact messages.

A batch of texts is one byte array in which every text ends with a line feed, so
that words never cross texts. All functions take whole batches; none loops over words.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes that separate words: space and TAB to CR.
SPACES = b" \t\n\x0b\x0c\r"
U = np.uint64


def word_table(spaces: bytes = SPACES) -> np.ndarray:
    table = np.ones(256, bool)
    table[list(spaces)] = False
    return table


#: Lower-cases A-Z and turns every ASCII byte but digits and letters into a space.
ALNUM = bytes(
    b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256)
)


def flat(texts, change=None) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts (null: empty), each with a line feed, and the start of each text (one more at the end).

    ``change``: a function of bytes that keeps their number, or a translation table.
    Eight zero bytes follow, so that a word can be read eight bytes at a time.
    """
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts.cast(pa.large_binary()), b"")
    ended = pc.binary_join_element_wise(texts, pa.scalar(b"\n", pa.large_binary()), pa.scalar(b"", pa.large_binary()))
    if isinstance(ended, pa.ChunkedArray):
        ended = ended.combine_chunks()
    off = np.frombuffer(ended.buffers()[1], np.int64)[ended.offset : ended.offset + len(ended) + 1]
    data = ended.buffers()[2]
    raw = b"" if data is None or not len(off) else memoryview(data)[off[0] : off[-1]].tobytes()
    if change is not None:
        raw = raw.translate(change) if isinstance(change, bytes) else change(raw)
    return np.frombuffer(raw + bytes(8), np.uint8), off - off[0] if len(off) else np.zeros(1, np.int64)


def words(buf: np.ndarray, off: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of each word, and the index of each text's first word (one more at the end)."""
    inside = table[buf[: off[-1]]]
    edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    if len(inside) and inside[0]:
        edge = np.concatenate(([0], edge))
    start, end = edge[0::2], edge[1::2]
    return start, end, np.searchsorted(start, off)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit (the finaliser of a published hash)."""
    h = h ^ (h >> U(33))
    h = h * U(0xFF51AFD7ED558CCD)
    h ^= h >> U(33)
    h *= U(0xC4CEB9FE1A85EC53)
    h ^= h >> U(33)
    return h


def word_hashes(buf: np.ndarray, start: np.ndarray, end: np.ndarray, seed: int = 1) -> np.ndarray:
    """A 64-bit hash of each byte range, read eight bytes at a time."""
    n = end - start
    h = mix(n.astype(U) * U(0x9E3779B97F4A7C15) + U(seed))
    if not len(n):
        return h
    eight = np.ndarray((len(buf) - 7,), "<u8", buf, strides=(1,))
    live, at, left = None, start, n
    while True:
        chunk = eight[at]
        keep = np.minimum(left, 8).astype(U) * U(8)
        chunk = np.where(keep == 64, chunk, chunk & ((U(1) << (keep & U(63))) - U(1)))
        if live is None:
            h = mix(h ^ chunk)
        else:
            h[live] = mix(h[live] ^ chunk)
        more = np.flatnonzero(left > 8)
        if not len(more):
            return h
        live = more if live is None else live[more]
        at, left = at[more] + 8, left[more] - 8


def windows(h: np.ndarray, n: int, factor: int = 0x9E3779B97F4A7C15) -> np.ndarray:
    """A hash of every n consecutive words; position i is the window that starts at word i."""
    m = len(h) - n + 1
    if m <= 0:
        return np.zeros(0, U)
    out = h[:m].copy()
    for j in range(1, n):
        out *= U(factor)
        out += h[j : j + m]
    return mix(out)


def inside_text(first: np.ndarray, n: int, total: int) -> np.ndarray:
    """For each window start, whether its n words belong to one text."""
    m = total - n + 1
    if m <= 0:
        return np.zeros(0, bool)
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    return doc[:m] == doc[n - 1 :]


def covered(starts: np.ndarray, n: int | np.ndarray, total: int) -> np.ndarray:
    """Which of ``total`` words lie inside a window of n words that starts at one of ``starts``."""
    d = np.bincount(starts, minlength=total + 1) - np.bincount(starts + n, minlength=total + 1)
    return np.cumsum(d[:total]) > 0


def per_text(flags: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sum of a word-level array over each text."""
    c = np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))
    return c[first[1:]] - c[first[:-1]]


def pack(a: np.ndarray) -> bytes:
    """Unsigned integers as compressed byte planes; bytes that are all zero cost nothing."""
    a = np.ascontiguousarray(a)
    head = np.array([len(a), a.dtype.itemsize], "<i8").tobytes()
    if not len(a):
        return head
    planes = np.ascontiguousarray(a.view(np.uint8).reshape(len(a), a.dtype.itemsize).T).tobytes()
    return head + pa.compress(planes, codec="zstd", asbytes=True)


def unpack(b: bytes) -> np.ndarray:
    n, size = (int(x) for x in np.frombuffer(b[:16], "<i8"))
    dtype = np.dtype(f"u{size}")
    if not n:
        return np.zeros(0, dtype)
    planes = pa.decompress(b[16:], decompressed_size=n * size, codec="zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(planes, np.uint8).reshape(size, n).T).reshape(-1).view(dtype)


def pack_sorted(a: np.ndarray) -> bytes:
    """Sorted 64-bit integers as compressed differences."""
    d = a.copy()
    d[1:] -= a[:-1]
    return pack(d)


def unpack_sorted(b: bytes) -> np.ndarray:
    return np.cumsum(unpack(b), dtype=U)


def ranges(texts: pa.Array, most: int = 1 << 20):
    """Slices of an array of texts that sum to about ``most`` bytes each."""
    for part in slices(pa.table({"t": texts}), "t", most):
        yield part.column("t").combine_chunks()


def field(table: pa.RecordBatch, column: str, name: str) -> pa.Array:
    """A field of a struct column."""
    struct = table.column(column)
    return pc.struct_field(struct, struct.type.get_field_index(name))


def tidy() -> None:
    """Gives memory that freed arrays leave in allocators back; workers live on between stages."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def slices(table: pa.Table | pa.RecordBatch, column: str, most: int = 2 << 20, inside: str | None = None):
    """Row ranges of a table whose texts (of a column, or of a field of the struct column) sum to about ``most`` bytes."""
    texts = table.column(column) if inside is None else field(table, column, inside)
    size = pc.fill_null(pc.binary_length(texts), 0)
    size = np.asarray(size.to_numpy(zero_copy_only=False) if isinstance(size, pa.Array) else size.to_numpy(), np.int64)
    group = np.cumsum(size) // most
    cut = np.flatnonzero(group[1:] != group[:-1]) + 1
    lo = 0
    for hi in [*cut.tolist(), len(size)]:
        if hi > lo:
            yield table.slice(lo, hi - lo)
            tidy()
        lo = hi
