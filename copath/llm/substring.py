"""Substring dedup with fixed-block anchors.

Every document is cut into blocks of seven words; any thirteen consecutive words hold a
whole block. The blocks are the index, and every rolling window of seven words of every
document is a probe. Where a probe meets the index, the hit is extended: the windows
of thirteen words around it are compared by a 96-bit fingerprint (64 and 32 bits of hashes with seeds of their own), and overlapping equal windows
join into maximal repeats. A window is removed where a document with a smaller id starts
it too; the words inside removed windows go.

Null and empty texts have no words. Rows without id lose words to documents with an id
and take none from others. Rows that share an id do not take words from each other.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from copath.llm import exchange as X
from copath.llm import kernel as K
from copath.llm.store import write_table

TABLE = K.word_table()
LAST = np.iinfo(np.int64).max


class Part:
    """Words of a part's texts, and the keys that it exchanges."""

    def __init__(self, table: pa.Table, window: int):
        self.ids, texts = table.column("id"), table.column("text")
        self.buf, self.off = K.flat(texts)
        self.start, self.end, self.first = K.words(self.buf, self.off, TABLE)
        self.h = K.word_hashes(self.buf, self.start, self.end)
        self.window, self.block = window, (window + 1) // 2
        self.total = len(self.h)
        self.order = self.ids.fill_null(LAST).to_numpy()

    def probes(self) -> tuple[np.ndarray, np.ndarray]:
        """Keys of all rolling block windows, which of them are index blocks; and their positions."""
        key = K.windows(self.h, self.block)
        at = np.flatnonzero(K.inside_text(self.first, self.block, self.total))
        inner = at - np.repeat(self.first[:-1], np.diff(self.first))[at]
        return key[at], inner % self.block == 0, at

    def candidates(self, told: list[tuple[int, bytes]], n: int) -> tuple[np.ndarray, ...]:
        """Starts of the windows that hold a shared block, by fingerprint: position, key, check."""
        key, indexed, at = self.probes()
        uniq, _ = X.ask_shared(key, indexed, n)
        hot = np.zeros(self.total + 1, np.int64)
        hot[at[X.among(key, X.shared_keys(uniq, told, n))]] = 1
        run = np.concatenate(([0], np.cumsum(hot)))
        ok = K.inside_text(self.first, self.window, self.total)
        pos = np.flatnonzero(ok & (run[self.window - self.block + 1 :][: len(ok)] > run[: len(ok)]))
        a = K.windows(self.h, self.window)[pos]
        # A second hash, of word hashes with a seed of their own.
        other = K.word_hashes(self.buf, self.start, self.end, seed=2)
        b = (K.windows(other, self.window, 0xD6E8FEB86659FD93)[pos] >> K.U(32)).astype(np.uint32)
        order = np.lexsort((b, a))
        return pos[order], a[order], b[order]

    def groups(self, pos, a, b):
        """First row of each distinct window, and the smallest id that starts it here."""
        new = np.flatnonzero(np.concatenate(([True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])))) if len(a) else np.zeros(0, np.int64)
        doc = self.order[np.searchsorted(self.first, pos, "right") - 1]
        return new, doc, np.minimum.reduceat(doc, new) if len(new) else doc


def _reply(table: pa.Table) -> pa.Table:
    """A bucket's answer: for each window, whether another part starts it with a smaller id."""
    made, sent = [], []
    for p, x in zip(table.column("pid").to_pylist(), table.column("blob").to_pylist()):
        a, b, d = X.split(x)
        sent.append((p, K.unpack_sorted(a), K.unpack(b), K.unpack(d).view(np.int64)))
    if sent:
        a, b, d = (np.concatenate([s[i] for s in sent]) for i in (1, 2, 3))
        order = np.lexsort((b, a))
        sa, sb = a[order], b[order]
        new = np.flatnonzero(np.concatenate(([True], (sa[1:] != sa[:-1]) | (sb[1:] != sb[:-1]))))
        least = np.repeat(np.minimum.reduceat(d[order], new), np.diff(np.append(new, len(a))))
        beaten = np.empty(len(a), bool)
        beaten[order] = least < d[order]
        at = 0
        for s in sent:
            mask = beaten[at : at + len(s[1])]
            at += len(s[1])
            if mask.any():
                made.append((s[0], 1, X.bits(mask)))
    return X.answers(table.column("bucket")[0].as_py(), made)


def removed_words(docs: DataFrame, id_col="doc_id", text_col="text", window: int = 13, emit=None, schema: str = "id long, n_words long, n_removed long, kept string"):
    """One row per document through ``emit(part, removed)``; by default the kept words, joined by one space.

    ``removed`` marks the part's words that an earlier document's window covers.
    """
    rows, size = X.parts(docs, id_col, text_col)
    n = X.buckets_for(size / 5, 3e6)
    emit = emit or kept_text

    def ask(table: pa.Table) -> pa.Table:
        key, indexed, _ = Part(table, window).probes()
        return X.rows(table.column("pid")[0].as_py(), X.ask_shared(key, indexed, n)[1])

    def extend(table: pa.Table, told: pa.Table) -> pa.Table:
        if not table.num_rows:
            return X.rows(0, [])
        part, pid, got = Part(table, window), table.column("pid")[0].as_py(), X.by_kind(told, 0)
        pos, a, b = part.candidates(got, n)
        new, _, least = part.groups(pos, a, b)
        a, b = a[new], b[new]
        at = X.cuts(a, 64, n)
        made = [(i, 1, X.join([K.pack_sorted(a[lo:hi]), K.pack(b[lo:hi]), K.pack(least[lo:hi].view(np.uint64))])) for i, (lo, hi) in enumerate(zip(at[:-1].tolist(), at[1:].tolist())) if hi > lo]
        return X.rows(pid, made)

    def finish(table: pa.Table, told: pa.Table) -> pa.Table:
        if not table.num_rows:
            return emit(None, None)
        part = Part(table, window)
        gone = np.zeros(part.total, bool)
        got = X.by_kind(told, 0)
        if got:
            pos, a, b = part.candidates(got, n)
            new, doc, least = part.groups(pos, a, b)
            beaten, at = np.zeros(len(new), bool), X.cuts(a[new], 64, n)
            for i, x in X.by_kind(told, 1):
                beaten[at[i] : at[i + 1]] = X.from_bits(x, at[i + 1] - at[i])
            size = np.diff(np.append(new, len(a)))
            cut = np.repeat(beaten, size) | (doc > np.repeat(least, size))
            gone = K.covered(pos[cut], window, part.total)
        return emit(part, gone)

    told, _ = write_table(rows.groupBy("pid").applyInArrow(ask, X.MESSAGE).groupBy("bucket").applyInArrow(X.tell_shared, X.MESSAGE))
    again = rows.groupBy("pid").cogroup(told.groupBy("pid")).applyInArrow(extend, X.MESSAGE).groupBy("bucket").applyInArrow(_reply, X.MESSAGE)
    return rows.groupBy("pid").cogroup(told.unionByName(again).groupBy("pid")).applyInArrow(finish, schema)


def _kept(part: Part, gone: np.ndarray):
    raw = part.buf.tobytes()
    first, off = part.first.tolist(), part.off.tolist()
    lost = K.per_text(gone, part.first).tolist()
    for d in range(len(first) - 1):
        lo, hi = first[d], first[d + 1]
        if not lost[d]:
            yield b" ".join(raw[off[d] : off[d + 1]].split())
        else:
            at = np.flatnonzero(~gone[lo:hi]) + lo
            yield b" ".join([raw[s:e] for s, e in zip(part.start[at].tolist(), part.end[at].tolist())])


def kept_text(part: Part | None, gone: np.ndarray | None) -> pa.Table:
    made = [] if part is None else [x.decode() for x in _kept(part, gone)]
    none = pa.array([], pa.int64())
    return pa.table(
        {
            "id": none if part is None else part.ids,
            "n_words": none if part is None else pa.array(np.diff(part.first)),
            "n_removed": none if part is None else pa.array(K.per_text(gone, part.first)),
            "kept": pa.array(made, pa.string()),
        }
    )


def kept_digest(part: Part | None, gone: np.ndarray | None) -> pa.Table:
    made = [] if part is None else [hashlib.sha256(x).hexdigest() for x in _kept(part, gone)]
    none = pa.array([], pa.int64())
    return pa.table(
        {
            "doc_id": none if part is None else part.ids,
            "n_words": none if part is None else pa.array(np.diff(part.first)),
            "n_removed": none if part is None else pa.array(K.per_text(gone, part.first)),
            "kept_sha256": pa.array(made, pa.string()),
        }
    )


def report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every document."""
    docs, names = X.numbered(docs, options.get("id_col", "doc_id"))
    return X.renamed(removed_words(docs, emit=kept_digest, schema="doc_id long, n_words long, n_removed long, kept_sha256 string", **options), names, "doc_id")
