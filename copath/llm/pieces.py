"""SentencePiece encoding by unigram Viterbi over a double-array trie, and decoding.

The pieces come from a model file. The scores of a unigram model's file are log scores; a file
of merges has ranks in their place, so ``fit`` estimates log scores from all documents by
expectation-maximisation over all segmentations. The best segmentation is the one with the greatest sum of scores (ties: the piece that starts first). A character that no
piece covers costs ten less than the worst piece and becomes its UTF-8 bytes' pieces.
A space is the marker U+2581 and each text gets one in front.

No piece has a marker after another character, nor a character that appears in no longer
piece beside others, so that a text falls into chunks which can be segmented one by one
without changing the best path. Each chunk that a batch repeats is segmented once.

Null and empty texts have no pieces. A literal U+2581 is encoded like a space and decoded
as one, so such a text doesn't return; any other valid text does.
"""

from __future__ import annotations

import copy
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.llm import kernel as K
from copath.llm.store import drop_table, write_table

MARK = "▁"
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: Kinds of pieces in a model file (fixed values of its format).
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
PENALTY = 10.0
#: Bytes of text at a time: few enough for the arrays of a step to stay in a processor's cache.
SLICE = 1 << 19
#: Kind of model whose scores are ranks.
BPE = 2


class DoubleArray:
    """A trie over bytes in two arrays: the child of state s by byte c is base[s] + c, if check there is s."""

    def __init__(self, keys: list[bytes]):
        children: list[dict[int, int]] = [{}]
        leaf: dict[int, int] = {}
        for value, key in enumerate(keys):
            node = 0
            for c in key:
                nxt = children[node].get(c)
                if nxt is None:
                    nxt = children[node][c] = len(children)
                    children.append({})
                node = nxt
            leaf[node] = value
        # A node with several children goes behind all others; a node with one child fills the first gap.
        used, base, check, number = bytearray(b"\1"), {}, {}, {}
        slot, todo, low = {0: 0}, [0], 1
        for node in todo:
            kids, s = sorted(children[node]), slot[node]
            number[s] = leaf.get(node, -1)
            if not kids:
                continue
            if len(kids) == 1:
                while low < len(used) and used[low] or low <= kids[0]:
                    low += 1
                b = low - kids[0]
            else:
                b = max(1, len(used) - kids[0])
            used.extend(bytes(max(0, b + kids[-1] + 1 - len(used))))
            base[s] = b
            for c in kids:
                used[b + c] = 1
                check[b + c] = s
                slot[children[node][c]] = b + c
                todo.append(children[node][c])
        top = len(used) + 256
        self.base, self.check, self.value = np.zeros(top, np.int32), np.full(top, -1, np.int32), np.full(top, -1, np.int32)
        for array, filled in ((self.base, base), (self.check, check), (self.value, number)):
            array[list(filled)] = list(filled.values())

    def matches(self, buf: np.ndarray, at: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All keys that start at positions ``at`` and end by ``end``: index into ``at``, key length, key number."""
        who, state, depth, found = np.arange(len(at)), np.zeros(len(at), np.int64), 0, []
        while len(who):
            ok = at[who] + depth < end[who]
            who, state = who[ok], state[ok]
            nxt = self.base[state].astype(np.int64) + buf[at[who] + depth]
            ok = (self.check[nxt] == state) & (self.base[state] > 0)
            who, state = who[ok], nxt[ok]
            depth += 1
            v = self.value[state]
            hit = np.flatnonzero(v >= 0)
            found.append((who[hit], np.full(len(hit), depth), v[hit]))
        return tuple(np.concatenate(x) for x in zip(*found)) if found else (who, who, who)


class Memory:
    """Pieces of chunks that a task has met, by the chunks' hashes; emptied when it holds ``most`` of them, which costs time and no result."""

    def __init__(self, most: int = 1 << 18):
        self.most = most
        self.forget()

    def forget(self) -> None:
        self.keys, self.begin, self.count, self.ids = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int32)

    def holds(self, h: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(h), bool)
        return self.keys[np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)] == h

    def learn(self, h: np.ndarray, ids: np.ndarray, at: np.ndarray) -> None:
        """h: sorted hashes that aren't held yet."""
        to = np.searchsorted(self.keys, h)
        self.keys = np.insert(self.keys, to, h)
        self.begin = np.insert(self.begin, to, at[:-1] + len(self.ids))
        self.count = np.insert(self.count, to, np.diff(at))
        self.ids = np.concatenate((self.ids, ids.astype(np.int32)))

    def of(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(self.keys, h)
        return self.begin[at], self.count[at]

    def tidy(self) -> None:
        if len(self.keys) > self.most:
            self.forget()


class Model:
    """Pieces, scores and trie of a model file's bytes."""

    def __init__(self, raw: bytes):
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        proto.ParseFromString(raw)
        self.pieces = [p.piece for p in proto.pieces]
        self.scores = np.array([p.score for p in proto.pieces])
        kinds = [p.type for p in proto.pieces]
        self.ids = np.array([i for i, k in enumerate(kinds) if k in (NORMAL, USER)], np.int64)
        #: Whether scores are ranks of merges.
        self.ranked = proto.trainer_spec.model_type == BPE
        self.unknown = kinds.index(UNKNOWN)
        self.byte_id = np.full(256, self.unknown, np.int64)
        out = []
        for i, (p, k) in enumerate(zip(self.pieces, kinds)):
            if k == BYTE:
                self.byte_id[int(p[3:5], 16)] = i
                out.append(bytes([int(p[3:5], 16)]))
            else:
                out.append(b"" if k in (CONTROL, UNKNOWN) else p.replace(MARK, " ").encode())
        self.fallback = bool((self.byte_id != self.unknown).all())
        keys = [self.pieces[i].replace(MARK, " ").encode() for i in self.ids]
        self.trie = DoubleArray(keys)
        self.least = self.scores[self.ids].min() - PENALTY
        text = np.frombuffer(b"".join(out) + b"\0", np.uint8)
        self.text, self.text_at = text, np.concatenate(([0], np.cumsum([len(x) for x in out])))
        together = {c for k in keys if len(k.decode()) > 1 for c in k if c < 128}
        #: ASCII characters that never share a piece with others.
        self.alone = np.array([c < 128 and c not in together for c in range(256)])
        if any(b" " in k.lstrip(b" ") for k in keys):
            raise ValueError("a piece holds a marker after another character; chunks would not be independent")

    def scored(self, scores: np.ndarray) -> Model:
        """The same pieces with other scores."""
        out = copy.copy(self)
        out.scores, out.least = scores, scores[self.ids].min() - PENALTY
        return out

    def _edges(self, buf: np.ndarray, lo: np.ndarray, hi: np.ndarray):
        """All pieces in the byte ranges, laid end to end: bytes, index of each in its range, where ranges begin; begin, end, id (-1: none) and score of the pieces."""
        size = hi - lo
        to = np.concatenate(([0], np.cumsum(size)))
        total = int(to[-1])
        inner = np.arange(total) - np.repeat(to[:-1], size)
        data = buf[np.repeat(lo, size) + inner]
        stop = np.repeat(to[1:], size)
        at = np.flatnonzero(data & 0xC0 != 0x80)
        who, length, key = self.trie.matches(data, at, stop[at])
        # Characters that no piece covers alone.
        width = np.minimum(np.append(at[1:], total) - at, stop[at] - at)
        single = np.zeros(len(at), bool)
        single[who[length == width[who]]] = True
        odd = np.flatnonzero(~single)
        begin = np.concatenate((at[who], at[odd]))
        finish = begin + np.concatenate((length, width[odd]))
        token = np.concatenate((self.ids[key], np.full(len(odd), -1)))
        score = np.concatenate((self.scores[self.ids[key]], np.full(len(odd), self.least)))
        return data, inner, to, begin, finish, token, score

    def expected(self, buf: np.ndarray, lo: np.ndarray, hi: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, float]:
        """Expected uses of each piece over all segmentations of the byte ranges, each ``times`` over, and their log likelihood."""
        size = hi - lo
        # Products of probabilities that can't vanish are taken as they are, others as logs.
        short = size * -self.least <= 700
        if short.any() and not short.all():
            (n, x), (m, y) = (self.expected(buf, lo[k], hi[k], times[k]) for k in (short, ~short))
            return n + m, x + y
        plain = bool(short.all())
        _, inner, to, begin, finish, token, score = self._edges(buf, lo, hi)
        of = np.repeat(np.arange(len(lo)), size)[begin]
        s, e = begin + of, finish + of
        first, last = to[:-1] + np.arange(len(lo)), to[1:] + np.arange(len(lo))
        most = int(size.max(initial=0))
        place, steps = inner[begin].astype(np.uint16 if most < 1 << 16 else np.int64), np.arange(most + 2)
        forth = np.full(int(to[-1]) + len(lo), 0.0 if plain else -np.inf)
        back = forth.copy()
        forth[first] = back[last] = 1.0 if plain else 0.0
        weight = np.exp(score) if plain else score

        def walk(order, cut, into, out, table):
            """A step's states to go to are distinct: no two pieces of a range begin and end together."""
            t, f, w = into[order], out[order], weight[order]
            for i, j in cut:
                x = t[i:j]
                table[x] = table[x] + table[f[i:j]] * w[i:j] if plain else np.logaddexp(table[x], table[f[i:j]] + w[i:j])

        order = np.argsort(place, kind="stable")
        cut = np.searchsorted(place[order], steps).tolist()
        walk(order, zip(cut[:-1], cut[1:]), e, s, forth)
        place = (place + (finish - begin)).astype(place.dtype)
        order = np.argsort(place, kind="stable")
        cut = [*np.searchsorted(place[order], steps).tolist(), len(place)]
        walk(order, zip(cut[-2::-1], cut[:0:-1]), s, e, back)
        ends = forth[last]
        if plain:
            use = forth[s] * weight * back[e] * (times / ends)[of]
            ends = np.log(ends)
        else:
            use = np.exp(forth[s] + weight + back[e] - ends[of]) * times[of]
        known = token >= 0
        return np.bincount(token[known], use[known], len(self.pieces)), float((ends * times).sum())

    def segment(self, buf: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Best pieces of the byte ranges: ids of all, and where each range's ids begin (one more at the end)."""
        size = hi - lo
        data, inner, to, begin, finish, token, score = self._edges(buf, lo, hi)
        total = int(to[-1])
        place = inner[begin]
        order = np.argsort(place, kind="stable")
        begin, finish, token, score = begin[order], finish[order], token[order], score[order]
        step = np.searchsorted(place[order], np.arange(int(size.max(initial=0)) + 1))
        # State i is the boundary before byte i of a range; a range's end has a state of its own.
        shift = np.repeat(np.arange(len(lo)), size)
        s, e = begin + shift[begin], finish + shift[begin]
        best = np.full(total + len(lo), -np.inf)
        best[to[:-1] + np.arange(len(lo))] = 0.0
        back, via = np.zeros(len(best), np.int64), np.zeros(len(best), np.int64)
        for i, j in zip(step[:-1].tolist(), step[1:].tolist()):
            if i < j:
                cand = best[s[i:j]] + score[i:j]
                up = np.flatnonzero(cand > best[e[i:j]]) + i
                to_state = e[up]
                best[to_state] = cand[up - i]
                back[to_state], via[to_state] = s[up], token[up]
        live = np.flatnonzero(size > 0)
        pos, first = (to[1:] + np.arange(len(lo)))[live], (to[:-1] + np.arange(len(lo)))[live]
        rows, toks, froms = [], [], []
        while len(live):
            rows.append(live)
            toks.append(via[pos])
            froms.append(back[pos])
            pos = back[pos]
            on = pos > first
            live, pos, first = live[on], pos[on], first[on]
        if not rows:
            return np.zeros(0, np.int64), np.zeros(len(lo) + 1, np.int64)
        row, tok, frm = np.concatenate(rows), np.concatenate(toks), np.concatenate(froms)
        order = np.lexsort((frm, row))
        row, tok, frm = row[order], tok[order], frm[order] - row[order]
        unk = tok < 0
        if unk.any() and self.fallback:
            wide = np.ones(len(tok), np.int64)
            lead = data[frm[unk]]
            w = 1 + (lead >= 0xC0).astype(np.int64) + (lead >= 0xE0) + (lead >= 0xF0)
            wide[unk] = w
            start = np.concatenate(([0], np.cumsum(wide)))
            rep = np.repeat(np.arange(len(tok)), wide)
            byte = data[np.minimum(frm[rep] + np.arange(start[-1]) - start[rep], total - 1)]
            tok = np.where(unk[rep], self.byte_id[byte], tok[rep])
            row = row[rep]
        else:
            tok = np.where(unk, self.unknown, tok)
        return tok, np.searchsorted(row, np.arange(len(lo) + 1))

    def chunks(self, texts):
        """Chunks of all texts: bytes, begin and end of each, where each text begins, a chunk of each distinct kind, each chunk's kind, and the kinds' hashes (sorted)."""
        if isinstance(texts, pa.ChunkedArray):
            texts = texts.combine_chunks()
        raw = pc.fill_null(texts.cast(pa.large_binary()), b"")
        made = [b" " + x if x else b"" for x in raw.to_pylist()]
        mark = MARK.encode()
        flat = b"".join(made)
        if mark in flat:
            made = [x.replace(mark, b" ") for x in made]
            flat = b"".join(made)
        length = np.fromiter(map(len, made), np.int64, len(made))
        off = np.concatenate(([0], np.cumsum(length))).astype(np.int64)
        buf = np.frombuffer(flat + bytes(8), np.uint8)
        n = int(off[-1])
        if not n:
            none = np.zeros(0, np.int64)
            return buf, none, none, off, none, none, none.view(np.uint64)
        b = buf[:n]
        begin = self.alone[b]
        begin[1:] |= self.alone[b[:-1]]
        space = b == 32
        begin |= space
        begin[1:] &= ~(space[1:] & space[:-1]) | self.alone[b[1:]]
        begin[off[:-1][length > 0]] = True
        lo = np.flatnonzero(begin)
        hi = np.append(lo[1:], n)
        h, one, which = np.unique(K.word_hashes(buf, lo, hi), return_index=True, return_inverse=True)
        return buf, lo, hi, off, one, which, h

    def encode(self, texts, memory: Memory | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Piece ids of all texts, and where each text's ids begin (one more at the end). ``memory``: chunks that were segmented before."""
        buf, lo, hi, off, one, which, h = self.chunks(texts)
        if not len(lo):
            return np.zeros(0, np.int64), np.zeros(len(off), np.int64)
        memory = memory or Memory()
        new = ~memory.holds(h)
        if new.any():
            memory.learn(h[new], *self.segment(buf, lo[one[new]], hi[one[new]]))
        begin, count = memory.of(h)
        begin, count = begin[which], count[which]
        start = np.concatenate(([0], np.cumsum(count)))
        out = memory.ids[np.arange(start[-1]) + np.repeat(begin - start[:-1], count)]
        return out.astype(np.int64), start[np.searchsorted(lo, off)]

    def decode(self, ids: np.ndarray, at: np.ndarray) -> list[bytes]:
        """Texts of id lists: pieces joined, markers as spaces, byte pieces as bytes, without the first space."""
        size = np.diff(self.text_at)[ids]
        to = np.concatenate(([0], np.cumsum(size)))
        raw = self.text[np.arange(to[-1]) + np.repeat(self.text_at[ids] - to[:-1], size)].tobytes()
        cut = to[at].tolist()
        return [raw[a + raw.startswith(b" ", a, b) : b] for a, b in zip(cut[:-1], cut[1:])]


_MODELS: dict[bytes, Model] = {}


def load(spark, path: str = DEFAULT_MODEL):
    """The model as a broadcast: some hundred kilobytes that don't grow with the data."""
    with open(path, "rb") as f:
        raw = f.read()
    key = hashlib.sha256(raw).digest()
    if key not in _MODELS:
        _MODELS[key] = Model(raw)
    return spark.sparkContext.broadcast(_MODELS[key])


#: Uses that every piece has besides those in the documents, so that unused ones keep a score.
SPARE = 0.01
#: Relative gain of the log likelihood under which the scores have settled.
SETTLED = 1e-4
#: How much farther than expectation-maximisation each round goes; a round that loses likelihood is taken back and all later ones go as far as it says.
REACH = 1.3


def fit(docs: DataFrame, text_col="text", model_path: str = DEFAULT_MODEL):
    """The file's pieces with log scores, as a broadcast: a unigram model's own ones, else from all documents.

    The distinct chunks of all texts are counted once. The first scores are the logs of how often a piece's text occurs in them; then
    expected uses over all segmentations give new ones, by steps that are stretched by ``REACH``, until the likelihood of the documents settles.
    """
    spark = docs.sparkSession
    start = load(spark, model_path)
    if not start.value.ranked:
        return start

    def count(batches):
        seen = Tally()
        for whole in batches:
            for b in K.slices(whole, "text", SLICE):
                buf, lo, hi, _, one, which, h = start.value.chunks(b.column("text"))
                raw, first, last = buf.tobytes(), lo[one].tolist(), hi[one].tolist()
                seen.add(h, np.bincount(which, minlength=len(one)), lambda i: raw[first[i] : last[i]])  # noqa: B023
                if len(seen.raw) > 1 << 18:
                    yield seen.batch()
                    seen = Tally()
        yield seen.batch()

    found = docs.select(F.col(text_col).alias("text")).mapInArrow(count, "chunk binary, n long")
    chunks, path = write_table(found.groupBy("chunk").agg(F.sum("n").alias("n")))
    ids = start.value.ids

    def uses(model, first):
        def one(batches):
            n, likelihood = np.zeros(len(start.value.pieces)), 0.0
            for whole in batches:
                for b in K.slices(whole, "chunk", 1 << 16):
                    raw = b.column("chunk").to_pylist()
                    to = np.concatenate(([0], np.cumsum([len(x) for x in raw]))).astype(np.int64)
                    buf, times = np.frombuffer(b"".join(raw) + bytes(8), np.uint8), b.column("n").to_numpy()
                    if first:
                        _, _, _, begin, _, token, _ = model.value._edges(buf, to[:-1], to[1:])
                        w = times[np.searchsorted(to, begin, "right") - 1]
                        n += np.bincount(token[token >= 0], w[token >= 0], len(n))
                    else:
                        more, gain = model.value.expected(buf, to[:-1], to[1:], times)
                        n, likelihood = n + more, likelihood + gain
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1), pa.int32()), pa.array(np.append(n[at], likelihood))], ["piece", "n"])

        # Sorted, so that sums don't depend on the order in which tasks end.
        t = chunks.mapInArrow(one, "piece int, n double").groupBy("piece").agg(F.sort_array(F.collect_list("n")).alias("n")).select("piece", F.aggregate("n", F.lit(0.0), lambda x, y: x + y).alias("n")).toArrow()
        piece, n = t.column("piece").to_numpy(), t.column("n").to_numpy()
        total = np.zeros(len(start.value.pieces))
        total[piece[piece >= 0]] = n[piece >= 0]
        return total, float(n[piece < 0].sum())

    def learned(total):
        scores = start.value.scores.copy()
        share = total[ids] + SPARE
        scores[ids] = np.round(np.log(share / share.sum()), 6)
        return Fitted(start, spark.sparkContext.broadcast(scores))

    total, _ = uses(start, True)
    model, plain, before, reach = learned(total), total, None, REACH
    while True:
        found, now = uses(model, False)
        if before is not None and now < before and reach > 1:
            # Too far: back to where the last round's own counts lead.
            reach, total, now = 1.0, plain, before
        elif before is not None and now - before <= SETTLED * abs(before):
            break
        else:
            share = lambda x: (x[ids] + SPARE) / (x[ids] + SPARE).sum()
            step, plain, last = np.ones(len(found)), found, total
            step[ids] = np.clip(share(found) / share(last), 1e-3, 1e3) ** (reach - 1)
            total = found * step
        before = now
        model.scores.destroy()
        model = learned(total)
    drop_table(spark, path)
    return model


class Tally:
    """How often a task has met each chunk, by the chunks' hashes."""

    def __init__(self):
        self.keys, self.n, self.row, self.raw = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), []

    def add(self, h: np.ndarray, n: np.ndarray, chunk_of) -> None:
        """h: sorted hashes, n: uses of each; chunk_of(i): bytes of the i-th."""
        at = np.searchsorted(self.keys, h)
        known = np.zeros(len(h), bool)
        if len(self.keys):
            known = self.keys[np.minimum(at, len(self.keys) - 1)] == h
        self.n[at[known]] += n[known]
        new = np.flatnonzero(~known)
        if len(new):
            rows = np.arange(len(self.raw), len(self.raw) + len(new))
            self.raw += [chunk_of(i) for i in new.tolist()]
            self.keys, self.n, self.row = (np.insert(x, at[new], y) for x, y in ((self.keys, h[new]), (self.n, n[new]), (self.row, rows)))

    def batch(self) -> pa.RecordBatch:
        n = np.empty(len(self.raw), np.int64)
        n[self.row] = self.n
        return pa.RecordBatch.from_arrays([pa.array(self.raw, pa.binary()), pa.array(n)], ["chunk", "n"])


class Fitted:
    """A model under other scores: one broadcast of pieces and trie serves all of them."""

    def __init__(self, base, scores):
        self.base, self.scores = base, scores

    def __getstate__(self):
        return {"base": self.base, "scores": self.scores}

    @property
    def value(self) -> Model:
        if "_made" not in self.__dict__:
            self._made = self.base.value.scored(self.scores.value)
        return self._made


def _lists(ids: np.ndarray, at: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids, pa.int32()))


def encode(docs: DataFrame, text_col="text", model_path: str = DEFAULT_MODEL, out_col="piece_ids", decoded_col: str | None = None, model=None) -> DataFrame:
    """The rows with their texts' piece ids, and, if it is named, the text that these decode to.

    All other columns stay (those named like a new one are replaced). Without a ``model`` of ``fit`` the file's scores count.
    """
    model = model or load(docs.sparkSession, model_path)
    kind = "ids array<int>, back string" if decoded_col else "ids array<int>"

    # Only the texts go to Python, and only what is new comes back.
    @F.arrow_udf(f"struct<{kind.replace('ids ', 'ids: ').replace('back ', 'back: ')}>")
    def one(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        memory = Memory()
        for texts in batches:
            made = []
            for part in K.ranges(texts, SLICE):
                memory.tidy()
                ids, at = model.value.encode(part, memory)
                fields = {"ids": _lists(ids, at)}
                if decoded_col:
                    fields["back"] = pa.array([x.decode(errors="replace") for x in model.value.decode(ids, at)], pa.string())
                made.append(pa.StructArray.from_arrays(list(fields.values()), list(fields)))
            yield pa.concat_arrays(made) if made else pa.array([], pa.struct([("ids", pa.list_(pa.int32()))] + ([("back", pa.string())] if decoded_col else [])))

    rest = [c for c in docs.columns if c not in (out_col, decoded_col)]
    out = docs.select(*[F.col(f"`{c}`") for c in rest], one(F.col(text_col)).alias("_new"))
    new = [F.col("_new.ids").alias(out_col)] + ([F.col("_new.back").alias(decoded_col)] if decoded_col else [])
    return out.select(*[F.col(f"`{c}`") for c in rest], *new)


def decode(encoded: DataFrame, ids_col="piece_ids", model_path: str = DEFAULT_MODEL, out_col="decoded") -> DataFrame:
    """The rows with the text that their piece ids stand for (null ids: empty); bytes that aren't UTF-8 become U+FFFD."""
    model = load(encoded.sparkSession, model_path)
    rest = [c for c in encoded.columns if c != out_col]
    packed = encoded.select(F.struct(*[F.col(f"`{c}`") for c in rest]).alias("row"), F.coalesce(F.col(ids_col), F.array().cast("array<int>")).alias("ids"))

    def one(batches):
        for whole in batches:
            for lo in range(0, whole.num_rows, 500):
                b = whole.slice(lo, 500)
                ids = b.column("ids")
                at = ids.offsets.to_numpy().astype(np.int64)
                texts = model.value.decode(ids.values.to_numpy(zero_copy_only=False)[at[0] : at[-1]].astype(np.int64), at - at[0])
                yield pa.RecordBatch.from_arrays([b.column("row"), pa.array([x.decode(errors="replace") for x in texts], pa.string())], ["row", "text"])

    row_type = packed.schema["row"].dataType.simpleString()
    out = packed.mapInArrow(one, f"row {row_type}, text string")
    return out.select(*[F.col(f"row.`{c}`").alias(c) for c in rest], F.col("text").alias(out_col))


def report(docs: DataFrame, id_col="doc_id", text_col="text", model_path: str = DEFAULT_MODEL) -> DataFrame:
    """doc_id, n_pieces, n_bytes (byte pieces), score, pieces_sha256 (ids as little-endian 32-bit), returns (whether decoding gives the text)."""
    model = fit(docs, text_col, model_path)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))

    def one(batches):
        memory = Memory()
        for whole in batches:
            for b in K.slices(whole, "text", SLICE):
                m = model.value
                memory.tidy()
                ids, at = m.encode(b.column("text"), memory)
                raw = ids.astype("<u4").tobytes()
                cut = (at * 4).tolist()
                is_byte = np.isin(np.arange(len(m.pieces)), m.byte_id)
                score = np.concatenate(([0.0], np.cumsum(m.scores[ids])))
                texts = pc.fill_null(b.column("text").cast(pa.large_binary()), b"").to_pylist()
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column("id"),
                        pa.array(np.diff(at), pa.int64()),
                        pa.array(K.per_text(is_byte[ids], at), pa.int64()),
                        pa.array(score[at[1:]] - score[at[:-1]]),
                        pa.array([hashlib.sha256(raw[i:j]).hexdigest() for i, j in zip(cut[:-1], cut[1:])], pa.string()),
                        pa.array([x == y for x, y in zip(m.decode(ids, at), texts)], pa.bool_()),
                    ],
                    ["doc_id", "n_pieces", "n_bytes", "score", "pieces_sha256", "returns"],
                )

    kind = rows.schema["id"].dataType.simpleString()
    return rows.mapInArrow(one, f"doc_id {kind}, n_pieces long, n_bytes long, score double, pieces_sha256 string, returns boolean")
