"""Toxicity by class-conditional Kneser-Ney models.

Two bigram models, toxic and ordinary, are interpolated level by level: a word after its predecessor (by texts that hold the pair); the
word by how many different predecessors the class shows it after; its first bytes, longer and then shorter, by how many different words of the class begin with
them, times the share that the longer form has of the shorter one over both classes; and the shortest beginning over both classes, with one unseen. Each
level has modified Kneser-Ney discounts, pairs and words that are too rare in both classes together go to the next level whole, and shares
are the same in both, so that a rare expression says little. Every model's probabilities sum to one after any word. A text's
evidence is the difference of its two length-normalised log-likelihoods, over the whole text and over its best passages of ``PASSAGES`` words; a
logistic curve turns it into a score from 0 to 1. The curve is fitted, and the lengths of beginnings are chosen, on evidence that models of
the other folds give for each labelled text.

Only labelled rows that ``learn`` admits are used: of each class, in the order of a hash of their ids, at most ``per_class`` and at most
half of ``most_bytes`` of text, up to the first one that doesn't fit (texts that no budget could hold are passed over). That is the bounded
sample. Texts are scored whole. Null, empty and word-less texts have no evidence and get the curve's value for that. Where the
sample lacks a class, all scores are the share of toxic labels (no labels: 0.1); a class of fewer texts than folds has no curve, and the score is
that of the plain sum of evidence and log odds of the labels.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.llm import kernel as K
from copath.llm.store import free_name

TABLE = K.word_table()
FOLDS = 3
#: Words of the passages that are looked at besides the whole text.
PASSAGES = (1, 4, 16)
FEATURES = len(PASSAGES) + 1
#: Key of what comes before a text's first word.
START = np.uint64(0x9E3779B97F4A7C15)


#: Bytes of the beginnings that a word falls back to, in turn; the labelled sample chooses one of these chains.
CHAINS = ((4,), (5,), (6, 4))
#: Texts that hold a pair, and predecessors of a word, under which the level leaves it to the next.
LEAST_PAIR, LEAST_WORD = 5, 3


def tokenised(texts, stems: tuple[int, ...]) -> tuple[np.ndarray, ...]:
    """Hash of each word, of the word before it (START at a text's beginning) and of its beginnings (a row each), and where each text begins."""
    buf, off = K.flat(texts, K.ALNUM)
    start, end, first = K.words(buf, off, TABLE)
    word = K.word_hashes(buf, start, end)
    before = np.concatenate(([START], word[:-1]))[: len(word)]
    before[first[:-1][np.diff(first) > 0]] = START
    return word, before, np.stack([K.word_hashes(buf, start, np.minimum(end, start + k), seed=9 + k) for k in stems]), first


def pair_keys(before: np.ndarray, word: np.ndarray) -> np.ndarray:
    return K.mix(before * K.U(31) + word)


def discounts(n: np.ndarray) -> np.ndarray:
    """Discount of counts 0, 1, 2 and 3 or more, from how many forms have each count."""
    k = [float((n == i).sum()) for i in range(1, 5)]
    if min(k) == 0:
        return np.array([0.0, 0.75, 0.75, 0.75])
    y = k[0] / (k[0] + 2 * k[1])
    return np.array([0.0, *(min(max(i - (i + 1) * y * k[i] / k[i - 1], 0.05 * i), 0.95 * i) for i in (1, 2, 3))])


def split_mass(n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Counts less their discounts, and the discounts."""
    d = np.minimum(discounts(n)[np.minimum(n, 3).astype(np.int64)], n)
    return n - d, d


def find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where each wanted key is, and whether it is there."""
    if not len(keys):
        return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return at, keys[at] == wanted


def level(n: np.ndarray, below: np.ndarray, rare: np.ndarray) -> tuple[np.ndarray, float]:
    """Probabilities by one class's counts n interpolated with those below; and the weight of what lies below. Rare forms keep no count."""
    left, freed = split_mass(n)
    left, freed = np.where(rare, 0.0, left), np.where(rare, n, freed)
    whole = n.sum()
    if not whole:
        return below, 1.0
    return left / whole + freed.sum() / whole * below, float(freed.sum() / whole)


class Forms:
    """Words, or beginnings of one length: their parents (shorter forms), and over both classes their share of the parent and what is left for new ones."""

    def __init__(self, keys: np.ndarray, parents: np.ndarray, parent_keys: np.ndarray):
        self.keys, one, where = np.unique(keys, return_index=True, return_inverse=True)
        self.parent = np.searchsorted(parent_keys, parents[one])
        n = np.bincount(where, minlength=len(self.keys)).astype(float)
        left, freed = split_mass(n)
        whole = np.bincount(self.parent, weights=n, minlength=len(parent_keys))
        fresh = np.bincount(self.parent, weights=freed, minlength=len(parent_keys)) / np.maximum(whole, 1.0)
        # A parent whose forms free nothing has no room for new ones: it gets some, and all shares make way.
        self.fresh = np.maximum(fresh, 1e-3)
        self.share = left / whole[self.parent] * ((1 - self.fresh) / np.maximum(1 - fresh, 1e-300))[self.parent]


class Model:
    """Both classes' probabilities (ordinary, toxic) as tables by pair, by word before, by word and by the word's beginnings."""

    def __init__(self, texts: list, labels: np.ndarray, stem_bytes: tuple[int, ...] = CHAINS[0]):
        self.curve, self.stem_bytes = np.zeros(FEATURES + 1), stem_bytes
        self.curve[0] = 1.0
        by = [tokenised(pa.array([t for t, y in zip(texts, labels) if y == c], pa.string()), stem_bytes) for c in (0, 1)]
        word, before, stems = (np.concatenate([x[i] for x in by], -1) for i in range(3))
        # From the shortest beginning up to the word.
        chain = [*stems[::-1], word]
        top = np.unique(chain[0])
        self.forms = [Forms(longer, shorter, np.unique(shorter)) for shorter, longer in zip(chain, chain[1:])]
        self.top = top
        # The word's row in each level, from the word down to the shortest beginning.
        up = [np.arange(len(self.forms[-1].keys))]
        for f in reversed(self.forms):
            up.append(f.parent[up[-1]])
        up = up[::-1]
        kinds = np.bincount(up[0], minlength=len(top)).astype(float)
        left, freed = split_mass(kinds)
        total = max(kinds.sum(), 1.0)
        base = np.append(left, 0.0) / total + (freed.sum() / total if len(top) else 1.0) / (len(top) + 1)
        words = self.forms[-1].keys
        follows = []
        for w, u, _, first in by:
            key, at, where = np.unique(pair_keys(u, w), return_index=True, return_inverse=True)
            text = np.repeat(np.arange(len(first) - 1), np.diff(first))
            held = np.unique(where.astype(np.int64) * (len(first) + 1) + text) // (len(first) + 1)
            follows.append((key, np.bincount(held, minlength=len(key)).astype(float), np.searchsorted(words, w[at]), u[at]))
        after = [np.bincount(w, minlength=len(words)).astype(float) for _, _, w, _ in follows]
        rare = after[0] + after[1] < LEAST_WORD
        #: Probabilities of each level's forms, the unseen shortest beginning last of its level; and the weight of what lies below each level.
        self.levels, self.back = [np.zeros((2, len(base)))], [np.ones(2)]
        for c in (0, 1):
            mine = np.bincount(up[0][after[c] > 0], minlength=len(top)).astype(float)
            self.levels[0][c] = level(np.append(mine, 0.0), base, np.zeros(len(base), bool))[0]
        for j, f in enumerate(self.forms, 1):
            last = j == len(self.forms)
            p, back = np.zeros((2, len(f.keys))), np.ones(2)
            for c in (0, 1):
                n = after[c] if last else np.bincount(up[j][after[c] > 0], minlength=len(f.keys)).astype(float)
                p[c], back[c] = level(n, self.levels[-1][c][f.parent] * f.share, rare if last else np.zeros(len(n), bool))
            self.levels.append(p)
            self.back.append(back)
        keys = np.concatenate([x[0] for x in follows])
        self.pairs, where = np.unique(keys, return_inverse=True)
        texts_with = np.bincount(where, weights=np.concatenate([x[1] for x in follows]), minlength=len(self.pairs))
        often = texts_with >= LEAST_PAIR
        self.before = np.unique(before)
        self.ahead, self.rest = np.zeros((2, len(self.pairs)), np.float32), np.ones((2, len(self.before)))
        for c, (key, n, _, u) in enumerate(follows):
            at, by_word = np.searchsorted(self.pairs, key), np.searchsorted(self.before, u)
            left = np.where(often[at], split_mass(n)[0], 0.0)
            seen = np.bincount(by_word, weights=n, minlength=len(self.before))
            self.ahead[c, at] = left / seen[by_word]
            self.rest[c] = 1 - np.bincount(by_word, weights=left, minlength=len(self.before)) / np.maximum(seen, 1.0)
        self.pairs, self.ahead = self.pairs[often], self.ahead[:, often]

    def probabilities(self, word: np.ndarray, before: np.ndarray, stems: np.ndarray) -> np.ndarray:
        """Of each word after the one before it, in both models; a word that no class has is the new form of its longest known beginning."""
        at, known = find(self.top, stems[-1])
        alone = self.levels[0][:, np.where(known, at, len(self.top))]
        for f, p, back, keys in zip(self.forms, self.levels[1:], self.back[1:], [*stems[-2::-1], word]):
            new = np.where(known, f.fresh[at] if len(f.fresh) else 1.0, 1.0) * back[:, None] * alone
            at, here = find(f.keys, keys)
            alone = np.where(here, p[:, at], new) if len(f.keys) else new
            known = here
        u, seen = find(self.before, before)
        rest = np.where(seen, self.rest[:, u], 1.0) if len(self.before) else np.ones((2, len(word)))
        k, both = find(self.pairs, pair_keys(before, word))
        ahead = np.where(both, self.ahead[:, k], 0.0) if len(self.pairs) else np.zeros((2, len(word)))
        return ahead + rest * alone

    def evidence(self, texts) -> np.ndarray:
        """Per text: the difference of the length-normalised log-likelihoods, and the largest such difference of its passages."""
        word, before, stems, first = tokenised(texts, self.stem_bytes)
        p = np.log(self.probabilities(word, before, stems))
        run = np.concatenate(([0.0], np.cumsum(p[1] - p[0])))
        n = np.diff(first)
        out = np.zeros((len(n), FEATURES + 1))
        out[:, -1] = 1
        out[:, 0] = (run[first[1:]] - run[first[:-1]]) / np.maximum(n, 1)
        for k, size in enumerate(PASSAGES, 1):
            # Starts of passages that lie in one text; shorter texts are their own passage.
            out[:, k] = out[:, 0]
            full = np.flatnonzero(n >= size)
            if len(full):
                mean = (run[size:] - run[:-size]) / size
                edges = np.stack((first[:-1][full], first[1:][full] - size + 1), 1).ravel()
                out[full, k] = np.maximum.reduceat(np.append(mean, -np.inf), edges)[::2]
        return out

    def fit(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
        """Logistic curve by Newton steps with a small ridge, on standardised evidence; gives its mean log loss."""
        mean, scale = x[:, :-1].mean(0), x[:, :-1].std(0) + 1e-9
        z = np.column_stack(((x[:, :-1] - mean) / scale, np.ones(len(x))))
        w = np.zeros(FEATURES + 1)
        ridge = np.diag([*[0.05] * FEATURES, 1e-3])
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            g = z.T @ (weight * (p - y)) + ridge @ w
            h = (z * (weight * p * (1 - p))[:, None]).T @ z + ridge
            step = np.linalg.solve(h, g)
            w -= step
            if np.abs(step).max() < 1e-8:
                break
        self.curve = np.append(w[:-1] / scale, w[-1] - (w[:-1] * mean / scale).sum())
        p = np.clip(1 / (1 + np.exp(-np.clip(z @ w, -30, 30))), 1e-12, 1 - 1e-12)
        return float(-(weight * (y * np.log(p) + (1 - y) * np.log(1 - p))).sum() / weight.sum())

    def score(self, texts) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.evidence(texts) @ self.curve, -30, 30)))


class Constant:
    def __init__(self, value: float):
        self.value = value

    def score(self, texts) -> np.ndarray:
        return np.full(len(texts), self.value)


def train(docs: DataFrame, labels: DataFrame, id_col="doc_id", text_col="text", label_col="toxic", learn: str = "true", per_class: int = 2000, most_bytes: int = 12 << 20):
    """A model from the bounded sample of labelled rows whose id (``id``) satisfies the SQL condition ``learn``."""
    marked = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("y")).where(F.expr(f"coalesce({learn}, false)") & F.col("y").isin(0, 1))
    marked = marked.groupBy("id").agg(F.max("y").alias("y"))
    totals = {r.y: r["count"] for r in marked.groupBy("y").count().collect()}
    if len(totals) < 2:
        return Constant(float(max(totals)) if totals else 0.1)
    picked = None
    for y in (0, 1):
        some = marked.where(F.col("y") == y).orderBy(F.xxhash64("id"), "id").limit(per_class)
        picked = some if picked is None else picked.union(some)
    names = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    rows = names.join(F.broadcast(picked), "id")  # at most 2 * per_class rows
    sizes = rows.select("id", "y", F.coalesce(F.octet_length("text"), F.lit(0)).alias("n"), F.xxhash64("id").alias("h")).dropDuplicates(["id"]).collect()
    wanted, left, over = [], {0: most_bytes // 2, 1: most_bytes // 2}, set()
    for r in sorted(sizes, key=lambda r: (r.h, r.id)):
        if r.y in over or r.n > most_bytes // 2:
            continue
        if r.n > left[r.y]:
            over.add(r.y)
            continue
        left[r.y] -= r.n
        wanted.append(r.id)
    ids = docs.sparkSession.createDataFrame([(i,) for i in wanted], rows.select("id").schema)
    got = rows.join(F.broadcast(ids), "id", "left_semi").dropDuplicates(["id"]).withColumn("fold", F.abs(F.xxhash64("id", F.lit("fold"))) % FOLDS).orderBy(F.xxhash64("id"), "id").toArrow()
    y, fold = got.column("y").to_numpy(), got.column("fold").to_numpy()
    if len(set(y.tolist())) < 2:
        return Constant(totals[1] / (totals[0] + totals[1]))
    model = learned(got.column("text").combine_chunks(), y, fold, totals)
    del got
    K.tidy()
    return model


def learned(texts: pa.Array, y: np.ndarray, fold: np.ndarray, totals: dict[int, int]) -> Model:
    """The model of a sample, by the chain of beginnings and the curve that serve best for texts of a fold under models of the others."""
    # The curve is for the labels' own proportion, not the sample's.
    weight = np.where(y == 1, totals[1] / max(1, (y == 1).sum()), totals[0] / max(1, (y == 0).sum())) * len(y) / (totals[0] + totals[1])
    best = None
    for stems in CHAINS:
        seen, judged = np.zeros((len(y), FEATURES + 1)), np.zeros(len(y), bool)
        for k in range(FOLDS):
            own, others = np.flatnonzero(fold == k), np.flatnonzero(fold != k)
            if len(own) and len(set(y[others].tolist())) == 2:
                part = Model(texts.take(pa.array(others)).to_pylist(), y[others], stems)
                judged[own] = True
                for i in range(0, len(own), 500):
                    seen[own[i : i + 500]] = part.evidence(texts.take(pa.array(own[i : i + 500])))
                del part
                K.tidy()
        if min((y[judged] == c).sum() for c in (0, 1)) < FOLDS:
            break
        curve = Model([], np.zeros(0))
        loss = curve.fit(seen[judged], y[judged].astype(float), weight[judged])
        if best is None or loss < best[0]:
            best = loss, stems, curve.curve
    model = Model(texts.to_pylist(), y, best[1] if best else CHAINS[0])
    if best:
        model.curve = best[2]
    else:
        model.curve[-1] = np.log(totals[1] / totals[0])
    return model


def score(docs: DataFrame, model, text_col="text", out_col="score") -> DataFrame:
    """The rows with their scores; all other columns stay (one named like ``out_col`` is replaced)."""
    known = docs.sparkSession.sparkContext.broadcast(model)

    # Only the texts go to Python, and only scores come back.
    @F.arrow_udf("double")
    def one(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield pa.array(np.concatenate([known.value.score(part) for part in K.ranges(texts)] or [np.zeros(0)]), pa.float64())

    rest = [c for c in docs.columns if c != out_col]
    return docs.select(*[F.col(f"`{c}`") for c in rest], one(F.col(text_col)).alias(out_col))


HELD_OUT = "crc32(cast({} AS string)) % 4 = 2"


def report(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, **options) -> DataFrame:
    """doc_id, held_out, score, predicted of every document; learns from labelled rows that aren't held out."""
    model = train(docs, labels, learn=f"NOT ({HELD_OUT.format('id')})", **options)
    out = score(docs.select("doc_id", "text"), model).select("doc_id", F.coalesce(F.expr(HELD_OUT.format("doc_id")), F.lit(False)).alias("held_out"), "score")
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def reject(docs: DataFrame, model, threshold: float = 0.3, text_col="text") -> DataFrame:
    """The documents that score below the threshold."""
    name = free_name(docs, "toxicity")
    return score(docs, model, text_col, name).where(F.col(name) < threshold).drop(name)
