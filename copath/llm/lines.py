"""Line dedup by a deletion neighbourhood.

Two lines are near if one word edit (insert, delete, replace) turns one into the other, and
both have at least ``min_words`` words; shorter lines are near only if their words are equal.
A line emits, as hashed keys, itself and every variant with one word deleted. Equal keys mean: same line; one line is the other without a word; or both
lack the word at the same place, so that they differ by a replacement. Key equality is the edit
distance: the key holds the length and the place, and a hit counts only if a second 32-bit hash with word and place seeds of its own
agrees, 96 bits in all. Words aren't shipped to compare them. A line goes where an
earlier line (smaller document id, then smaller line number) is near; decisions are made on
the input, not on what is left.

Lines end at line feeds; words are runs of bytes other than white space. Lines without words
always stay. Null and empty texts have one line without words. Rows without an id come
after all others; between rows that share an id, the line number decides, and at equal
line numbers both stay.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from copath.llm import exchange as X
from copath.llm import kernel as K
from copath.llm.store import free_name, write_table

TABLE = K.word_table()
LAST = np.iinfo(np.int64).max
SELF, LESS, GAP = 0, 1, 2  # the line itself; a line without one word, as a line; a line with a gap at a place


class Part:
    """Lines of a part's texts, and the keys that it exchanges."""

    def __init__(self, table: pa.Table, min_words: int):
        self.table, self.min_words = table, min_words
        self.buf, self.off = K.flat(table.column("text"))
        start, end, _ = K.words(self.buf, self.off, TABLE)
        # A line ends at each line feed; each text ends with one.
        self.stop = np.flatnonzero(self.buf[: self.off[-1]] == 10)
        self.begin = np.concatenate(([0], self.stop[:-1] + 1))
        doc = np.searchsorted(self.off, self.begin, "right") - 1
        self.number = np.arange(len(self.begin)) - np.searchsorted(self.begin, self.off[:-1])[doc]
        self.first = np.searchsorted(start, np.append(self.begin, self.off[-1]))
        self.n = np.diff(self.first)
        self.h = K.word_hashes(self.buf, start, end)
        self.id = table.column("id").fill_null(LAST).to_numpy()[doc] if len(doc) else np.zeros(0, np.int64)
        self.inner = np.arange(len(self.h)) - np.repeat(self.first[:-1], self.n)
        self.span = start, end
        self.key = Sums(self, self.h, 0x243F6A8885A308D3)
        self._check = None

    @property
    def check(self) -> Sums:
        """A second hash, of word hashes and places with seeds of their own."""
        if self._check is None:
            self._check = Sums(self, K.word_hashes(self.buf, *self.span, seed=2), 0x13198A2E03707344)
        return self._check

    def selves(self) -> tuple[np.ndarray, ...]:
        """Of each line with words, sorted: key, check, id, number, line."""
        line = np.flatnonzero(self.n > 0)
        key, check = self.key.whole(line), short(self.check.whole(line))
        order = np.lexsort((self.number[line], self.id[line], check, key))
        line = line[order]
        return key[order], check[order], self.id[line], self.number[line], line

    def halves(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Keys of halves, sorted, with the key of the whole line; and the line.

        Two lines within one word edit agree in the first or the second half of the shorter one.
        """
        keys, lines = [], []
        for less in (0, 1):
            line = np.flatnonzero(self.n - less >= self.min_words)
            n = self.n[line] - less
            a = n // 2
            size = n.astype(np.uint64) * K.U(0xC2B2AE3D27D4EB4F)
            keys += [K.mix(K.mix(self.key.head(line, a) + size)), K.mix(K.mix(self.key.tail(line, n - a) + size) + K.U(1))]
            lines += [line, line]
        self.key._rear = None
        key, line = np.concatenate(keys), np.concatenate(lines)
        whole = self.key.whole(line)
        order = np.lexsort((whole, key))
        return key[order], whole[order], line[order]

    def variants(self, line: np.ndarray) -> tuple[np.ndarray, ...]:
        """Keys of the lines, of the lines without one word, and of the lines with a gap; sorted.

        Key, check, side (0: the line itself, 1: one that lacks a word), id, number, line, whether of a gap.
        """
        wide = line[self.n[line] > self.min_words]
        parts = [(self.key.whole(line), self.check.whole(line), line, SELF)]
        for chosen, kind in ((wide, LESS), (line, GAP)):
            at, of = words_of(self, chosen)
            parts.append((self.key.without(at, of, kind == GAP), self.check.without(at, of, kind == GAP), of, kind))
        key, of = np.concatenate([x[0] for x in parts]), np.concatenate([x[2] for x in parts])
        check = short(np.concatenate([x[1] for x in parts]))
        kind = np.concatenate([np.full(len(x[0]), x[3]) for x in parts])
        side = (kind != SELF).astype(np.uint8)
        order = np.lexsort((self.number[of], self.id[of], side, check, key))
        of = of[order]
        return key[order], check[order], side[order], self.id[of], self.number[of], of, (kind == GAP)[order]


def short(h: np.ndarray) -> np.ndarray:
    return (h >> K.U(32)).astype(np.uint32)


def words_of(part: Part, line: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of the lines' words, and the line of each."""
    n = part.n[line]
    to = np.concatenate(([0], np.cumsum(n)))
    return np.arange(to[-1]) + np.repeat(part.first[line] - to[:-1], n), np.repeat(line, n)


class Sums:
    """Hashes of word sequences from running sums of one pseudo-random number for each (word, place).

    Beginnings count places from the line's start, ends from its end; behind a word that is left out, places move up by one.
    As every place has numbers of its own, no rearrangement of words keeps a sum but by chance.
    """

    def __init__(self, part: Part, h: np.ndarray, seed: int):
        self.part, self.h, self.seed = part, h, K.U(seed)
        self.fore = self.run(part.inner)
        self._less = self._rear = None

    def run(self, place: np.ndarray) -> np.ndarray:
        own = K.mix(self.h + place.astype(np.uint64) * K.U(0x9E3779B97F4A7C15) + self.seed)
        return np.concatenate((np.zeros(1, np.uint64), np.cumsum(own, dtype=np.uint64)))

    @property
    def less(self) -> np.ndarray:
        if self._less is None:
            self._less = self.run(self.part.inner - 1)
        return self._less

    @property
    def rear(self) -> np.ndarray:
        if self._rear is None:
            self._rear = self.run(np.repeat(self.part.n, self.part.n) - 1 - self.part.inner)
        return self._rear

    def head(self, line, a):
        at = self.part.first[line]
        return self.fore[at + a] - self.fore[at]

    def tail(self, line, b):
        to = self.part.first[line + 1]
        return self.rear[to] - self.rear[to - b]

    def finish(self, h, n, gap=None):
        """The key says how many words there are, and where the gap is if there is one."""
        if gap is None:
            return K.mix(K.mix(h + n.astype(np.uint64) * K.U(0xA24BAED4963EE407)))
        return K.mix(K.mix(h + n.astype(np.uint64) * K.U(0x9FB21C651E98DF25)) + gap.astype(np.uint64))

    def whole(self, line):
        return self.finish(self.head(line, self.part.n[line]), self.part.n[line])

    def without(self, at, line, gap: bool):
        """Lines without the word at position ``at``; as a line of its own, or with a gap there."""
        n, end = self.part.n[line], self.part.first[line + 1]
        behind = self.fore if gap else self.less
        h = self.fore[at] - self.fore[self.part.first[line]] + behind[end] - behind[at + 1]
        return self.finish(h, n, self.part.inner[at]) if gap else self.finish(h, n - 1)


def runs(*columns: np.ndarray) -> np.ndarray:
    n = len(columns[0])
    if not n:
        return np.zeros(0, np.int64)
    new = np.zeros(n, bool)
    new[0] = True
    for c in columns:
        new[1:] |= c[1:] != c[:-1]
    return np.flatnonzero(new)


def earliest(key, check, side, ids, number):
    """The earliest (id, number) on each side of every key, spread to all rows: ids and numbers of both sides. Rows come sorted."""
    new = runs(key, check)
    size = np.diff(np.append(new, len(key)))
    both = runs(key, check, side)
    first = {s: both[side[both] == s] for s in (0, 1)}
    out = []
    for s in (0, 1):
        i, j = np.full(len(new), LAST), np.full(len(new), np.iinfo(np.int64).max)
        g = np.searchsorted(new, first[s], "right") - 1
        i[g], j[g] = ids[first[s]], number[first[s]]
        out.append((np.repeat(i, size), np.repeat(j, size)))
    return out


def before(i, j, ids, number):
    return (i < ids) | ((i == ids) & (j < number))


def _first_reply(table: pa.Table) -> pa.Table:
    """Kind 1: whether an equal line comes earlier in another part. Kind 3: whether a different line has the half."""
    made, whole, half, sized = [], [], [], 0
    for p, k, x in zip(table.column("pid").to_pylist(), table.column("kind").to_pylist(), table.column("blob").to_pylist()):
        if k == 7:
            sized += int(np.frombuffer(x, ">i8")[0])
            continue
        x = X.split(x)
        if k == 1:
            whole.append((p, K.unpack_sorted(x[0]), K.unpack(x[1]), K.unpack(x[2]).view(np.int64), K.unpack(x[3]).astype(np.int64)))
        else:
            half.append((p, K.unpack_sorted(x[0]), K.unpack(x[1])))
    if whole:
        key, check, ids, number = (np.concatenate([s[i] for s in whole]) for i in range(1, 5))
        order = np.lexsort((number, ids, check, key))
        new = runs(key[order], check[order])
        size = np.diff(np.append(new, len(key)))
        i, j = np.repeat(ids[order][new], size), np.repeat(number[order][new], size)
        beaten = np.empty(len(key), bool)
        beaten[order] = before(i, j, ids[order], number[order])
        made += marks(whole, beaten, 1)
    if half:
        key, line = (np.concatenate([s[i] for s in half]) for i in (1, 2))
        order = np.lexsort((line, key))
        sk, sl = key[order], line[order]
        new = runs(sk)
        size = np.diff(np.append(new, len(sk)))
        shared = np.empty(len(key), bool)
        shared[order] = np.repeat(sl[new] != sl[new + size - 1], size)
        made += marks(half, shared, 3)
        made.append((-1, 8, X.count_of(int(shared.sum()))))
    made.append((-1, 7, X.count_of(sized)))
    return X.answers(table.column("bucket")[0].as_py(), made)


def marks(sent: list[tuple], mask: np.ndarray, kind: int) -> list[tuple[int, int, bytes]]:
    made, at = [], 0
    for s in sent:
        own = mask[at : at + len(s[1])]
        at += len(s[1])
        if own.any():
            made.append((s[0], kind, X.bits(own)))
    return made


def _second_reply(table: pa.Table) -> pa.Table:
    """For each row sent (a part's earliest line on one side of a key): the earliest line of both sides anywhere."""
    made, sent = [], []
    for p, x in zip(table.column("pid").to_pylist(), table.column("blob").to_pylist()):
        a, b, c, d, e = X.split(x)
        sent.append((p, K.unpack_sorted(a), K.unpack(b), K.unpack(c), K.unpack(d).view(np.int64), K.unpack(e).astype(np.int64)))
    if sent:
        key, check, side, ids, number = (np.concatenate([s[i] for s in sent]) for i in range(1, 6))
        order = np.lexsort((number, ids, side, check, key))
        best = earliest(key[order], check[order], side[order], ids[order], number[order])
        back = [np.empty(len(key), np.int64) for _ in range(4)]
        for (i, j), bi, bj in zip(best, back[0::2], back[1::2]):
            bi[order], bj[order] = i, j
        at = 0
        for s in sent:
            to = slice(at, at + len(s[1]))
            at = to.stop
            made.append((s[0], 4, X.join([K.pack(x[to].view(np.uint64)) for x in back])))
    return X.answers(table.column("bucket")[0].as_py(), made)


def spread(told: list[tuple[int, bytes]], at: np.ndarray, total: int) -> np.ndarray:
    mask = np.zeros(total, bool)
    for b, x in told:
        mask[at[b] : at[b + 1]] = X.from_bits(x, at[b + 1] - at[b])
    return mask


def first_round(part: Part, n: int):
    """What a part sends first, by bucket: its distinct lines with their earliest place, and its halves. With all rows, for the answers."""
    key, check, ids, number, line = part.selves()
    new = runs(key, check)
    hk, hw, hl = part.halves()
    hnew = runs(hk, hw)
    return (key, check, ids, number, line, new, X.cuts(key[new], 64, n)), (hk, hw, hl, hnew, X.cuts(hk[hnew], 64, n))


def after_first(part: Part, told: pa.Table, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Lines that repeat an earlier one word for word; and the others that share a half with a different line."""
    (key, check, ids, number, line, new, at), (hk, _, hl, hnew, hat) = first_round(part, n)
    gone = np.zeros(len(part.begin), bool)
    if len(key):
        size = np.diff(np.append(new, len(key)))
        own = before(np.repeat(ids[new], size), np.repeat(number[new], size), ids, number)
        gone[line[np.repeat(spread(X.by_kind(told, 1), at, len(new)), size) | own]] = True
    near = np.zeros(len(part.begin), bool)
    if len(hk):
        size = np.diff(np.append(hnew, len(hk)))
        near[hl[np.repeat(spread(X.by_kind(told, 3), hat, len(hnew)), size)]] = True
    return gone, np.flatnonzero(near & ~gone)


def dedup(docs: DataFrame, id_col="doc_id", text_col="text", min_words: int = 5, emit=None, schema="id long, n_lines long, n_removed long, text string", extra: str | None = None) -> DataFrame:
    """One row per document through ``emit(part, gone)``; by default the lines that stay. ``gone`` marks the part's lines.

    First, equal lines meet, and halves: two lines within one edit share one. Only the earliest of equal
    lines, and only if a different line shares a half, then emits its deletion neighbourhood.

    extra: a struct column of ``docs`` that goes with each row, unread.
    """
    more = [F.col(f"`{text_col}`").isNull().alias("was_null"), F.col(extra).alias("extra")] if extra else []
    last, size = X.parts(docs, id_col, text_col, *more, part_bytes=2 << 20)
    rows = last.select("pid", "id", "text")
    n = X.buckets_for(size / 12)
    emit = emit or kept_lines
    empty = to_arrow_schema(T.StructType.fromDDL(schema)).empty_table()

    def ask(table: pa.Table) -> pa.Table:
        part = Part(table, min_words)
        (key, check, ids, number, _, new, at), (hk, hw, _, hnew, hat) = first_round(part, n)
        key, check, ids, number, hk, hw = key[new], check[new], ids[new], number[new], hk[hnew], hw[hnew]
        made = [(b, 1, X.join([K.pack_sorted(key[i:j]), K.pack(check[i:j]), K.pack(ids[i:j].view(np.uint64)), K.pack(number[i:j].astype(np.uint32))])) for b, (i, j) in enumerate(zip(at[:-1].tolist(), at[1:].tolist())) if j > i]
        made += [(b, 3, X.join([K.pack_sorted(hk[i:j]), K.pack(hw[i:j])])) for b, (i, j) in enumerate(zip(hat[:-1].tolist(), hat[1:].tolist())) if j > i]
        # Halves and the words behind them tell how large the second round can get.
        made.append((0, 7, X.count_of(int(part.n[part.n >= min_words].sum()))))
        return X.rows(table.column("pid")[0].as_py(), made)

    def compare(table: pa.Table, told: pa.Table) -> pa.Table:
        if not table.num_rows:
            return X.rows(0, [])
        part = Part(table, min_words)
        key, check, side, ids, number, *_ = part.variants(after_first(part, told, n)[1])
        new = runs(key, check, side)  # the earliest of each side; rows come sorted
        key, check, side, ids, number = (x[new] for x in (key, check, side, ids, number))
        at = X.cuts(key, 64, wide)
        made = [(b, 4, X.join([K.pack_sorted(key[i:j]), K.pack(check[i:j]), K.pack(side[i:j]), K.pack(ids[i:j].view(np.uint64)), K.pack(number[i:j].astype(np.uint32))])) for b, (i, j) in enumerate(zip(at[:-1].tolist(), at[1:].tolist())) if j > i]
        return X.rows(table.column("pid")[0].as_py(), made)

    def finish(table: pa.Table, told: pa.Table) -> pa.Table:
        if not table.num_rows:
            return empty
        part = Part(table, min_words)
        gone, near = after_first(part, told, n)
        if len(near):
            key, check, side, ids, number, line, gap = part.variants(near)
            new = runs(key, check, side)
            at = X.cuts(key[new], 64, wide)
            best = [np.full(len(new), LAST) for _ in range(4)]
            for b, x in X.by_kind(told, 4):
                for to, y in zip(best, X.split(x)):
                    to[at[b] : at[b + 1]] = K.unpack(y).view(np.int64)
            size_of = np.diff(np.append(new, len(key)))
            i0, j0, i1, j1 = (np.repeat(b, size_of) for b in best)
            # A line meets lines that become it without a word; a line without a word meets lines, a gap meets gaps.
            gone[line[before(i0, j0, ids, number)]] = True
            gone[line[before(i1, j1, ids, number) & ((side == 0) | gap)]] = True
        return emit(part, gone)

    told, _ = write_table(rows.groupBy("pid").applyInArrow(ask, X.MESSAGE).groupBy("bucket").applyInArrow(_first_reply, X.MESSAGE))
    # Only lines that share halves send their neighbourhoods, two keys a word: no more than all words, and about as many as halves of lines of 128 words.
    wide = X.buckets_for(min(2.0 * X.tally(told, 7), X.tally(told, 8) * 256.0))
    told = told.where("pid >= 0")
    again = rows.groupBy("pid").cogroup(told.groupBy("pid")).applyInArrow(compare, X.MESSAGE).groupBy("bucket").applyInArrow(_second_reply, X.MESSAGE)
    return last.groupBy("pid").cogroup(told.unionByName(again).groupBy("pid")).applyInArrow(finish, schema)


def kept_texts(part: Part, gone: np.ndarray) -> list[bytes]:
    """Each text without its lines that go; untouched texts stay as they are, byte for byte."""
    raw, out = part.buf.tobytes(), []
    first = np.searchsorted(part.begin, part.off).tolist()
    off, begin, stop = part.off.tolist(), part.begin.tolist(), part.stop.tolist()
    for d in range(len(first) - 1):
        lo, hi = first[d], first[d + 1]
        g = gone[lo:hi]
        out.append(raw[off[d] : off[d + 1] - 1] if not g.any() else b"\n".join([raw[begin[i] : stop[i]] for i in (np.flatnonzero(~g) + lo).tolist()]))
    return out


def counts(part: Part, gone: np.ndarray) -> tuple[pa.Array, pa.Array]:
    first = np.searchsorted(part.begin, part.off)
    return pa.array(np.diff(first)), pa.array(K.per_text(gone, first))


def kept_lines(part: Part, gone: np.ndarray) -> pa.Table:
    n, lost = counts(part, gone)
    return pa.table({"id": part.table.column("id"), "n_lines": n, "n_removed": lost, "text": pa.array([x.decode() for x in kept_texts(part, gone)], pa.string())})


def kept_digest(part: Part, gone: np.ndarray) -> pa.Table:
    n, lost = counts(part, gone)
    return pa.table({"doc_id": part.table.column("id"), "n_lines": n, "n_removed": lost, "kept_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in kept_texts(part, gone)], pa.string())})


def report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_lines, n_removed, kept_sha256 (of the remaining lines, joined by line feeds) of every document."""
    docs, names = X.numbered(docs, options.get("id_col", "doc_id"))
    return X.renamed(dedup(docs, emit=kept_digest, schema="doc_id long, n_lines long, n_removed long, kept_sha256 string", **options), names, "doc_id")


def clean(docs: DataFrame, id_col="doc_id", text_col="text", min_words: int = 5) -> DataFrame:
    """The documents with their repeated lines removed; every row and all other columns stay."""
    row = free_name(docs, "row")
    packed = docs.withColumn(row, F.struct(*[F.col(f"`{c}`") for c in docs.columns if c != text_col]))
    row_type = packed.schema[row].dataType.simpleString()
    packed, _ = X.numbered(packed, id_col)

    def emit(part, gone):
        texts = [None if null else x.decode() for x, null in zip(kept_texts(part, gone), part.table.column("was_null").to_pylist())]
        return pa.table({"row": part.table.column("extra"), "text": pa.array(texts, pa.string())})

    out = dedup(packed, id_col, text_col, min_words, emit=emit, schema=f"row {row_type}, text string", extra=row)
    return out.select(*[F.col("text").alias(c) if c == text_col else F.col(f"row.`{c}`").alias(c) for c in docs.columns])
