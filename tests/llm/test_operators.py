"""The operators against brute force on small fixtures with nulls, empties, ties, repeats, long texts and clashing columns."""

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from copath.llm import components, decontaminate, embeddings, exchange, hmm, html, kernel, lines, pieces, simhash, substring, toxicity, warc
from copath.llm.store import write_table

WORDS = [f"w{i}" for i in range(60)] + ["É", "ö", "漢字", "x" * 40]


def make_texts(seed: int, n: int) -> list:
    rng = random.Random(seed)
    some = lambda k: " ".join(rng.choice(WORDS) for _ in range(k))
    passages = [some(20) for _ in range(4)]
    out = [None, "", "  \n\t ", "One", "one", some(3000)]
    while len(out) < n:
        t = "\n".join(some(rng.randint(0, 12)) for _ in range(rng.randint(1, 6)))
        if rng.random() < 0.4:
            t += rng.choice("\n ") + rng.choice(passages) + " " + some(2)
        out += [t] * (3 if rng.random() < 0.2 else 1)
        if rng.random() < 0.3 and len(t.split(" ")) > 3:
            w = t.split(" ")
            w[rng.randrange(len(w))] = "changed"
            out.append(" ".join(w))
    return out[:n]


@pytest.fixture(scope="module")
def texts():
    return make_texts(1, 120)


@pytest.fixture(scope="module")
def docs(spark, texts):
    rows = [(i, t, "id", 1) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, `row` string, hit int").repartition(5)


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def split(t):
    return re.findall("[^\x20\x09-\x0d]+", t or "")


def test_kernel_hashes_and_messages():
    import pyarrow as pa

    buf, off = kernel.flat(pa.array(["ab ab abcdefgh abcdefghi", None, "ab"]))
    s, e, first = kernel.words(buf, off, kernel.word_table())
    h = kernel.word_hashes(buf, s, e)
    assert first.tolist() == [0, 4, 4, 5] and h[0] == h[1] == h[4] and len(set(h.tolist())) == 3
    a = np.sort(np.random.default_rng(0).integers(0, 1 << 60, 999).astype(np.uint64))
    assert (kernel.unpack_sorted(kernel.pack_sorted(a)) == a).all() and len(kernel.unpack(kernel.pack(a[:0]))) == 0
    assert exchange.split(exchange.join([b"a", b"", b"bcd"])) == [b"a", b"", b"bcd"]


def test_components(spark):
    rng = random.Random(4)
    links = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + [(5, 5), (100, 101), (101, 100)]
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = {r.node: r.root for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: find(x) for x in parent if find(x) != x}
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


def brute_links(fps, bound):
    root = list(range(len(fps)))
    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= bound:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    return root


def test_simhash(docs, texts):
    want = []
    for t in texts:
        w = split(lower(t))
        sh = [" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in sh]
        want.append(sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)))
    got = {r.id: r for r in simhash.near_duplicates(docs).collect()}
    assert [got[i].fp % (1 << 64) for i in range(len(texts))] == want
    assert [got[i].component_id for i in range(len(texts))] == brute_links(want, 4)


@pytest.mark.parametrize("bound", [2, 4, 8])
def test_pigeonhole_loses_no_link(spark, bound):
    rng = np.random.default_rng(bound)
    base = rng.integers(0, 1 << 63, 40).astype(np.uint64)
    fps = [int(b) ^ sum(1 << int(k) for k in rng.choice(64, rng.integers(0, 2 * bound), replace=False)) for b in base for _ in range(8)]
    fps = sorted(set(fps))
    df = spark.createDataFrame([(simhash.signed(x),) for x in fps], "fp long")
    roots = {r.node: r.root for r in components.components(simhash.link_fingerprints(df, bound)).collect()}
    want = brute_links(fps, bound)
    groups = {}
    for x, r in zip(fps, want):
        groups.setdefault(r, set()).add(roots.get(simhash.signed(x), simhash.signed(x)))
    assert all(len(g) == 1 for g in groups.values()) and len(set().union(*groups.values())) == len(groups)


def test_dense_bucket_takes_blocks():
    rng = np.random.default_rng(0)
    fp = np.unique(np.array([sum(1 << int(k) for k in rng.choice(40, 3, replace=False)) for _ in range(900)], np.uint64))
    part, key, own = np.zeros(len(fp), np.int64), np.zeros(len(fp), np.int64), np.ones(len(fp), bool)
    a, b = simhash.group_links(part, key, fp, own, 4)
    root = simhash.local_roots(len(fp), np.searchsorted(fp, a), np.searchsorted(fp, b))
    link = np.bitwise_count(fp[:, None] ^ fp[None]) <= 4
    want = simhash.local_roots(len(fp), *np.nonzero(link))
    assert (root == want).all()


def test_keep_first(spark, docs, texts):
    texts = texts[:36]
    kept = {r.doc_id for r in simhash.keep_first(docs.where("doc_id < 36")).collect()}
    sets = [set(tuple(w[i : i + 5]) for i in range(len(w) - 4)) or ({tuple(w)} if w else set()) for w in (split(lower(t)) for t in texts)]
    same = lambda a, b: (not a and not b) or (a | b and len(a & b) / len(a | b) >= 0.8)
    assert 0 in kept
    for i, a in enumerate(sets):
        alone = not any(same(a, b) for j, b in enumerate(sets) if j != i)
        copy = any(texts[j] == texts[i] for j in range(i))
        assert not alone or i in kept
        assert not copy or i not in kept
    assert simhash.keep_first(docs.limit(0)).count() == 0
    twice = spark.createDataFrame([(1, "a b"), (1, "c d"), (None, "a b"), (None, None)], "doc_id long, text string")
    assert simhash.keep_first(twice).count() == 3


def test_substring(spark, docs, texts):
    first = {}
    for i, t in enumerate(texts):
        w = split(t)
        for k in range(len(w) - 12):
            first.setdefault(tuple(w[k : k + 13]), i)
    got = {r.doc_id: r for r in substring.report(docs).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        w = split(t)
        gone = [0] * len(w)
        for k in range(len(w) - 12):
            if first[tuple(w[k : k + 13])] < i:
                gone[k : k + 13] = [1] * 13
        kept = " ".join(x for x, g in zip(w, gone) if not g)
        assert (got[i].n_words, got[i].n_removed, got[i].kept_sha256) == (len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest())
    long = " ".join(WORDS[:20])
    odd = spark.createDataFrame([(None, long), (None, long), (5, long), (5, long)], "doc_id long, text string")
    assert sorted((r.doc_id or 0, r.n_removed) for r in substring.report(odd).collect()) == [(0, 20), (0, 20), (5, 0), (5, 0)]
    assert substring.report(docs.limit(0)).count() == 0


def near(a, b):
    if a == b:
        return True
    if min(len(a), len(b)) < 5 or abs(len(a) - len(b)) > 1:
        return False
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b)) == 1
    a, b = (a, b) if len(a) > len(b) else (b, a)
    return any(a[:i] + a[i + 1 :] == b for i in range(len(a)))


def test_lines(spark, docs, texts):
    seen, want = [], []
    for t in texts:
        keep = []
        for line in (t or "").split("\n"):
            w = split(line)
            if not w or not any(near(w, x) for x in seen):
                keep.append(line)
            if w:
                seen.append(w)
        want.append("\n".join(keep))
    got = {r.doc_id: r for r in lines.report(docs).collect()}
    assert [got[i].kept_sha256 for i in range(len(texts))] == [hashlib.sha256(x.encode()).hexdigest() for x in want]
    cleaned = {r.doc_id: r for r in lines.clean(docs).collect()}
    assert all(cleaned[i].text == (None if texts[i] is None else want[i]) and cleaned[i].row == "id" for i in range(len(texts)))
    assert lines.clean(docs.limit(0)).count() == 0 and lines.clean(docs).columns == docs.columns


def test_lines_tell_rearranged_words_apart(spark):
    """A sequence of two words and its complement, for which sums of powers modulo 2^64 are equal."""
    bits = [bin(i).count("1") & 1 for i in range(2048)]
    rows = [(1, " ".join("ab"[b] for b in bits)), (2, " ".join("ba"[b] for b in bits)), (3, " ".join("ab"[b] for b in bits))]
    got = {r.doc_id: r.n_removed for r in lines.report(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 0, 2: 0, 3: 1}
    got = {r.doc_id: r.n_removed for r in substring.report(spark.createDataFrame(rows[:2], "doc_id long, text string"), window=2047).collect()}
    assert got == {1: 0, 2: 0}


@pytest.mark.parametrize("which", [lines.report, substring.report, lambda d: hmm.score(d, table_words=20, sample_rounds=1, states=2)])
def test_ids_of_any_kind(spark, which):
    text = " ".join(WORDS[:20])
    rows = [("b", text), ("a", text), (None, text), (None, text), ("c", None), ("a", "x")]
    names = spark.createDataFrame(rows, "doc_id string, text string")
    out = which(names).collect()
    assert sorted(str(r.doc_id) for r in out) == ["None", "None", "a", "a", "b", "c"]
    if "n_removed" in out[0]:
        assert {(r.doc_id, r.n_removed > 0) for r in out} == {("a", False), ("b", True), (None, True), ("c", False)}
    assert which(names.limit(0)).count() == 0


def test_many_equal_rows_without_ids(spark):
    """Not one group: rows without an id are dealt one by one."""
    d = spark.range(3000).select(F.lit(None).cast("long").alias("doc_id"), F.lit("").alias("text")).union(spark.createDataFrame([(1, " ".join(WORDS) * 40)], "doc_id long, text string"))
    rows, _ = exchange.parts(d, "doc_id", "text", part_bytes=1 << 12)
    sizes = [r["count"] for r in rows.groupBy("pid").count().collect()]
    assert len(sizes) > 10 and max(sizes) < 600
    assert lines.report(d).count() == substring.report(d).count() == 3001


def test_dense_groups_are_cut_into_blocks(spark, monkeypatch):
    """Fingerprints of one probe group, more than a task holds: the same components as by brute force."""
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 62)
    fps = sorted({int(base) ^ sum(1 << int(b) for b in rng.choice(12, rng.integers(0, 4), replace=False)) for _ in range(300)} | {int(x) for x in rng.integers(0, 1 << 62, 50)})
    for held in (1 << 16, 40):
        monkeypatch.setattr(simhash, "HELD", held)
        monkeypatch.setattr(simhash.whole_groups, "__defaults__", (held,))
        frame = spark.createDataFrame([(i, x) for i, x in enumerate(fps)], "id long, fp long")
        got = {r.id: r.component_id for r in simhash.group_fingerprints(write_table(frame)[0], 4).collect()}
        root = list(range(len(fps)))
        changed = True
        while changed:
            changed = False
            for i, a in enumerate(fps):
                for j in range(i):
                    if bin(a ^ fps[j]).count("1") <= 4 and root[i] != root[j]:
                        root[i] = root[j] = min(root[i], root[j])
                        changed = True
        assert got == dict(enumerate(root))


def test_near_duplicates_with_clashing_names(spark):
    text = " ".join(WORDS[:30])
    d = spark.createDataFrame([(1, text, "a", "p"), (2, text, "b", "q"), (None, text, "c", "r"), (3, None, "d", "s"), (4, "", "e", "t")], "doc_id long, text string, _id string, gone string")
    out = simhash.keep_first(d)
    assert out.columns == d.columns and {r["_id"] for r in out.collect()} == {"a", "c", "d"}
    assert simhash.keep_first(d.limit(0)).count() == 0


def test_decontaminate_in_blocks(spark, docs, texts):
    """A benchmark of several blocks, one at a time, marks the same words."""
    own = [(f"i{k}", " ".join(split(t)[:14])) for k, t in enumerate(texts) if t and len(split(t)) > 14] + [("short", "one"), ("none", None), ("i0", "again " * 12)]
    b = spark.createDataFrame(own, "item_id string, text string")
    key = lambda d: sorted(map(tuple, d.collect()))
    assert key(decontaminate.report(docs, b)) == key(decontaminate.report(docs, b, block_bytes=400))


def test_decontaminate(spark, docs, texts):
    rng = random.Random(8)
    bench = [(1, "w1 W2"), (2, None), (3, "..!"), (10, " ".join(rng.choice(WORDS[:6]) for _ in range(14))), (4, texts[-1]), (None, "漢字")]
    item = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    windows = {}
    for k, t in bench:
        w = item.findall(lower(t))
        n = min(10, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            windows.setdefault(tuple(w[i : i + n]), set()).add("" if k is None else str(k))
    b = spark.createDataFrame(bench, "item_id long, text string")
    for block in (1 << 20, 8):
        got = {r.doc_id: r for r in decontaminate.report(docs, b, block_bytes=block).collect()}
        for i, t in enumerate(texts):
            w = item.findall(lower(t))
            hit, ids = [0] * len(w), set()
            for n in {len(x) for x in windows}:
                for k in range(len(w) - n + 1):
                    if x := windows.get(tuple(w[k : k + n])):
                        ids |= x
                        hit[k : k + n] = [1] * n
            r = got[i]
            assert (r.n_words, r.n_hit, r.n_items, r.contaminated) == (len(w), sum(hit), len(ids), sum(hit) > 0)
            assert r.items_sha256 == hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()
    clean = decontaminate.clean(docs, b)
    assert clean.columns == docs.columns
    assert decontaminate.report(clean.where("doc_id != 4"), b).where("n_hit >= 10").count() == 0
    untouched = {i for i in range(len(texts)) if not got[i].contaminated}
    assert {r.doc_id: r.text for r in clean.collect() if r.doc_id in untouched} == {i: texts[i] for i in untouched}
    assert decontaminate.report(docs, b.limit(0)).where("contaminated").count() == 0


def test_pieces(spark, docs, texts):
    with open(pieces.DEFAULT_MODEL, "rb") as f:
        m = pieces.Model(f.read())
    score = {m.pieces[i].replace("▁", " "): m.scores[i] for i in m.ids}
    longest = max(map(len, score))

    def best(text):
        text = " " + text
        top = [0.0] + [float("-inf")] * len(text)
        for i in range(len(text)):
            for j in range(i + 1, min(len(text), i + longest) + 1):
                s = score.get(text[i:j], m.least if j == i + 1 else None)
                if s is not None and top[i] + s > top[j]:
                    top[j] = top[i] + s
        return top[-1]

    got = {r.doc_id: r for r in pieces.encode(docs, decoded_col="decoded").collect()}
    for i, t in enumerate(texts):
        assert got[i].decoded == (t or "")
        if t and len(t) < 300 and not any(x in m.byte_id for x in got[i].piece_ids):
            assert sum(m.scores[x] for x in got[i].piece_ids) == pytest.approx(best(t))
    odd = spark.createDataFrame([(1, "a▁b"), (2, "\U0001f9ff\x01\n\n  x"), (3, "y" * 5000)], "doc_id long, text string")
    r = {x.doc_id: x for x in pieces.report(odd).collect()}
    assert not r[1].returns and r[2].returns and r[3].returns and r[2].n_bytes > 0
    back = pieces.decode(pieces.encode(docs)).where("decoded != coalesce(text, '')")
    assert back.count() == 0


def test_hmm(docs, texts):
    got = {r.doc_id: r for r in hmm.score(docs, table_words=50, sample_rounds=3, states=3).collect()}
    token = lambda t: [*split(lower(t)), None]
    learn = [t for i, t in enumerate(texts) if zlib.crc32(str(i).encode()) % 10]
    count = {}
    for t in learn:
        for w in token(t):
            count[w] = count.get(w, 0) + 1
    n, v = sum(count.values()), len(count)
    for i, t in enumerate(texts):
        r = got[i]
        base = sum(np.log10((count.get(w, 0) + 0.1) / (n + 0.1 * (v + 1))) for w in token(t))
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(token(t)), sum(w in count for w in token(t)), n)
        assert r.base_score == pytest.approx(base) and r.held_out == (zlib.crc32(str(i).encode()) % 10 == 0) and r.score < 0


def test_hmm_of_one_state_is_a_unigram_model(docs, texts):
    """All words in the table, one state: the score follows from counts alone; and repeats on other partitions."""
    got = {r.doc_id: r.score for r in hmm.score(docs, table_words=5000, states=1, sample_rounds=1).collect()}
    token = lambda t: [*split(lower(t)), None]
    count = {}
    for i, t in enumerate(texts):
        if zlib.crc32(str(i).encode()) % 10:
            for w in token(t):
                count[w] = count.get(w, 0) + 1
    n, once = sum(count.values()), sum(c == 1 for c in count.values())
    unseen = min(0.5, (once + 1) / (n + 2))
    for i, t in enumerate(texts):
        want = sum(np.log10(count[w] / n * (1 - unseen) if w in count else unseen) for w in token(t))
        assert got[i] == pytest.approx(want, rel=1e-4)
    again = {r.doc_id: r.score for r in hmm.score(docs.repartition(2), table_words=40, states=3, sample_rounds=3).collect()}
    other = {r.doc_id: r.score for r in hmm.score(docs.repartition(7), table_words=40, states=3, sample_rounds=3).collect()}
    assert all(again[i] == pytest.approx(other[i], rel=1e-9) for i in again)


def test_hmm_recursions():
    rng = np.random.default_rng(0)
    norm = lambda x, a: x / x.sum(a, keepdims=True)
    chain = hmm.Chain(norm(rng.random(3), 0), norm(rng.random((3, 3)), 1), norm(rng.random((7, 3)), 0))
    texts = [rng.integers(0, 7, k) for k in (1, 4, 4, 9)]

    def walk(t):
        paths = {(s,): chain.start[s] * chain.emit[t[0], s] for s in range(3)}
        for x in t[1:]:
            paths = {(*p, s): q * chain.step[p[-1], s] * chain.emit[x, s] for p, q in paths.items() for s in range(3)}
        return paths

    short = texts[:3]
    score, _ = hmm.forward(chain, short, False)
    starts, steps, emits, total = hmm.expected(chain, short)
    want_steps, want_starts, want_emits = np.zeros((3, 3)), np.zeros(3), np.zeros((7, 3))
    for k, t in enumerate(short):
        paths = walk(t)
        z = sum(paths.values())
        assert score[k] == pytest.approx(np.log10(z))
        for p, q in paths.items():
            want_starts[p[0]] += q / z
            for x, s in zip(t, p):
                want_emits[x, s] += q / z
            for a, b in zip(p, p[1:]):
                want_steps[a, b] += q / z
    assert np.allclose(steps, want_steps) and np.allclose(starts, want_starts) and np.allclose(emits, want_emits) and total == pytest.approx(score.sum())


def test_toxicity(spark):
    rng = random.Random(2)
    rows, labels = [], []
    for i in range(400):
        toxic = i % 5 == 0
        w = [rng.choice(WORDS) for _ in range(rng.randint(5, 60))]
        if toxic:
            w[rng.randrange(len(w))] = rng.choice(("vile", "nastyling", "nastyness"))
        rows.append((i, " ".join(w)))
        labels.append((i, int(toxic)))
    rows += [(1000, None), (1001, "")]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    lab = spark.createDataFrame([*labels, (77777, 1), (3, None)], "doc_id long, toxic int")
    got = {r.doc_id: r for r in toxicity.report(d, lab).collect()}
    assert len(got) == 402 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got.values())
    right = sum(got[i].predicted == y for i, y in labels if got[i].held_out)
    assert right >= 0.95 * sum(got[i].held_out for i, _ in labels) and got[1000].predicted == 0
    assert toxicity.report(d, lab.limit(0)).where("score = 0.1").count() == 402
    assert toxicity.report(d.limit(0), lab).count() == 0


def test_toxicity_models_sum_to_one():
    """After any word: all known words, a new word of each known beginning, and a word with a new beginning."""
    texts = ["a b c a b d abcdefgh abcdefgi", "the cat sat on the mat the cat", "idiot fool the cat idiot idiotic", "a b idiot a idiot x abcdxx abcdez"] * 4
    for stems in toxicity.CHAINS:
        m = toxicity.Model(texts, np.array([0, 0, 1, 1] * 4), stems)
        word, _, begin, _ = toxicity.tokenised(pa.array(sorted(set(" ".join(texts).split()))), stems)
        new = np.uint64(7)
        for before in (toxicity.START, word[0], word[3], np.uint64(12345)):
            total = m.probabilities(word, np.full(len(word), before), begin).sum(1)
            chains = {tuple(begin[::-1][: d + 1, i].tolist()) for i in range(len(word)) for d in range(len(stems))} | {()}
            for known in chains:
                fresh = [*known, *(5_000_000 + j for j in range(len(stems) - len(known)))][::-1]
                total = total + m.probabilities(np.array([new]), np.array([before]), np.array(fresh, np.uint64)[:, None]).sum(1)
            assert total == pytest.approx([1, 1], abs=1e-6)
    # A rare word of one class says less than one that many of its texts hold.
    p = m.probabilities(*[x[:1] if x.ndim == 1 else x[:, :1] for x in toxicity.tokenised(pa.array(["idiot"]), stems)[:3]])
    q = m.probabilities(*[x[:1] if x.ndim == 1 else x[:, :1] for x in toxicity.tokenised(pa.array(["fool"]), stems)[:3]])
    assert p[1] / p[0] > 2 and p[1] / p[0] > q[1] / q[0]


def test_toxicity_edges(spark):
    rng = random.Random(8)
    rows = [(i, " ".join(rng.choice(WORDS) for _ in range(30)) + (" vile" if i % 4 == 0 else ""), "x") for i in range(40)]
    rows += [(None, "vile", "y"), (0, rows[0][1], "z"), (999, "w1 " * 200_000 + "vile", "t")]
    d = spark.createDataFrame(rows, "doc_id long, text string, toxicity string")
    few = spark.createDataFrame([(i, int(i % 4 == 0)) for i in (0, 1, 2, 3, 4)], "doc_id long, toxic int")
    for labels in (few, few.where("toxic = 1"), few.where("toxic = 0"), few.limit(0)):
        model = toxicity.train(d, labels)
        kept = toxicity.reject(d, model)
        assert kept.columns == d.columns
        assert toxicity.score(d, model).where("score BETWEEN 0 AND 1").count() == len(rows)
    # Two texts that differ in length alone are both within the sample: it isn't the shortest ones that are taken.
    long = spark.createDataFrame([(i, "w " * (1000 if i % 2 else 10), i % 2) for i in range(40)], "doc_id long, text string, toxic int")
    assert isinstance(toxicity.train(long, long, most_bytes=40_000), toxicity.Model)


PAGE = """<!DOCTYPE html><html><head><title>t</title><style>p{}</style><script>var a = "<p>no</p>";</script></head><body>
<header><a href="/">Site name</a></header><nav><ul><li><a href=/a>Menu</a></li></ul></nav><div class="cookie-notice">We use cookies</div>
{open}<h1>Head&amp;line</h1><p>First   <b>bo</b>ld para &eacute; with words enough to count.<br>After</p><aside>Related things</aside><div class="ad">Buy now</div>
<p>Second para with still more words in it.<form><input> Subscribe</form>{close}<section id="comments"><p>A reader says hello</p></section><div class=sidebar>Side</div><footer>Foot</footer></body></html>"""
TEXT = "Head&line First bold para é with words enough to count. After Second para with still more words in it."


def test_html(spark):
    assert html.extract(PAGE.replace("{open}", "<article>").replace("{close}", "</article>")) == TEXT
    assert html.extract(PAGE.replace("{open}", '<div id="content">').replace("{close}", "</div>")) == TEXT
    assert [html.extract(x) for x in (None, "", "<p></p>", "<!-- a", "<script>x")] == [""] * 5
    rows = [(1, "u", PAGE.replace("{open}", "<main>").replace("{close}", "</main>"), "x"), (2, None, None, "y")]
    rows += [rows[0]] * 2 + [(3, "v", "<p>" + "long words " * 200_000, "z")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    out = html.report(pages).collect()
    got = {r.page_id: r for r in out}
    assert len(out) == 5 and sum(r.page_id == 1 and r.text == TEXT for r in out) == 3
    assert got[1].n_chars == len(TEXT) and got[2].text == "" and got[2].n_chars == 0 and got[3].text == ("long words " * 200_000).strip()
    assert html.report(pages.limit(0)).count() == 0


LONG = " ".join(["word"] * 30)


@pytest.mark.parametrize(
    "page, text",
    [
        ("<html><head><script>for(i=0;i<n;i++){x='a}</script></head><body><article><p>{}</p></article></body>", "{}"),
        ("<script>var a='<!-- x';</script><body><article><p>{}</p></article>", "{}"),
        ("<html><head><title>T</title><body><article><p>{}</p></article>", "{}"),
        ('<article><p>{} <a href="x>link</a> tail</p></article>', "{} link tail"),
        ('<article><p title="a > b">{} <img alt="x < y > z"> tail</p></article>', "{} tail"),
        ('<section class="wide more"><p>{}</p></section>', "{}"),
        ('<article><p>{}</p><div class="ad">buy now</div><p>end.</p></article>', "{} end."),
        ('<div class="content"><h1>Hi</h1><p>{}</p><p>Bye.</p></div><div class="comments">{} {} {}</div><footer>f</footer>', "Hi {} Bye."),
        ('<div class="with-sidebar"><div class="x"><h1>Hi</h1><p>{}</p></div><div class="sidebar">{}</div></div>', "Hi {}"),
        ("<nav>a b c</nav><h1>Hi</h1><p>{}</p><p>So.</p><footer>f</footer>", "Hi {} So."),
        ("<p>{}<template>no</template><noscript>no</noscript><iframe><p>no</iframe> &lt;b&gt; 1 < 2</p>", "{} <b> 1 < 2"),
    ],
)
def test_html_cases(page, text):
    assert html.extract(page.replace("{}", LONG)) == text.replace("{}", LONG)


def test_html_time_is_linear():
    import time

    for page in ('<p x="y>' * 40_000, "<p x='y>a" * 20_000 + '<b y="' * 20_000, "<div>" * 40_000 + "x" + "</div>" * 40_000 + "</p>" * 40_000, "<" * 200_000, '<a b="' + "<" * 200_000):
        began = time.monotonic()
        html.extract(page)
        assert time.monotonic() - began < 5


def test_best_segment_equals_all_segments():
    rng = random.Random(3)
    for _ in range(300):
        x = [rng.choice((-3.0, -1.0, -0.5, 0.0, 0.5, 1.0, 2.0)) for _ in range(rng.randint(0, 12))]
        i, j = html.best_segment(x)
        assert sum(x[i:j]) == max([0.0, *(sum(x[a:b]) for a in range(len(x)) for b in range(a + 1, len(x) + 1))])


def test_html_learns_from_labelled_pages(spark):
    """Marks hidden from the extractor, names of no list: what is inside is known from the labelled pages."""
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet").withColumn("html", F.regexp_replace("html", 'class="ad"', 'class="qzx"'))
    weights = html.weights_from(pages)
    assert weights[".qzx"] < -1 and weights["<p"] > weights["<li"] and weights["words"] > weights["link words"]
    direct = {r.page_id: r.text for r in html.main_text(pages, weights=weights).collect()}
    hidden = pages.withColumn("html", F.regexp_replace("html", "article", "div"))
    got = {r.page_id: r.text for r in html.main_text(hidden, weights=weights).collect()}
    assert got == direct and min(map(len, direct.values())) > 0


def test_warc(spark, tmp_path):
    page = '<html lang="de"><head><title>A &amp; B</title></head><body><p>One <b>two</b></p><p>Three</p><a href="/x?a&amp;b">l</a><!-- c --></body></html>'
    pages = spark.createDataFrame([(1, "http://a/", page), (2, "http://b/", None)], "page_id long, url string, html string")
    own = warc.responses_from_pages(pages)
    made = warc.derive(own).collect()
    assert len(made) == 4
    for r in made:
        assert r.refers_to == r.source_id and r.block_digest == warc.digest(r.block.encode()) and r.content_length == len(r.block.encode()) and r.source_headers.startswith("HTTP/1.1 200")
    by = {(r.target_uri, r.warc_type): r for r in made}
    assert by["http://a/", "conversion"].block == "One two\nThree\nl" and by["http://b/", "conversion"].block == ""
    assert '"title": "A & B", "language": "de", "links": ["/x?a&b"]' in by["http://a/", "metadata"].block
    assert by["http://a/", "metadata"].source_payload_digest == warc.digest(page.encode())
    # Files are read back as they were written, marks inside payloads, binary and empty ones included.
    odd = spark.createDataFrame(
        [("<urn:uuid:1>", "http://a/", "d", "HTTP/1.1 200 OK\r\nX: y\r\n", page.encode()), ("<urn:uuid:2>", "http://b/", "d", "HTTP/1.1 200 OK\r\n", b"\x00\xff\r\n\r\nWARC/1.1\r\n\r\nWARC/1.0 \xfe\n\n"), ("<urn:uuid:3>", "http://c/", "d", "HTTP/1.1 204 None\r\n", b"")],
        "record_id string, target_uri string, warc_date string, http_headers string, payload binary",
    )
    want = sorted((r.record_id, r.http_headers, bytes(r.payload), warc.digest(bytes(r.payload)), False) for r in odd.collect())
    for packed in (None, "gzip"):
        where = str(tmp_path / f"in_{packed}")
        warc.write_responses(odd, where, packed)
        read = warc.read_warc(spark, where)
        assert sorted((r.record_id, r.http_headers, bytes(r.payload), r.payload_digest, r.truncated) for r in read.collect()) == want
        made = warc.derive(read)
        out = str(tmp_path / f"out_{packed}")
        warc.write_warc(made, out, packed)
        files = [f for f in __import__("os").listdir(out) if f.startswith("part")]
        assert files and all(f.endswith(".warc.gz" if packed else ".warc") for f in files)
        back = {(r.refers_to, r.warc_type): r for r in warc.read_derivatives(spark, out).collect()}
        assert len(back) == 6
        for r in made.collect():
            x = back[r.refers_to, r.warc_type]
            assert (x.record_id, x.target_uri, x.warc_date, x.content_type, bytes(x.block), x.block_digest) == (r.record_id, r.target_uri, r.warc_date, r.content_type, r.block.encode(), warc.digest(r.block.encode()))
            assert x.source_payload_digest == r.source_payload_digest and x.source_block_digest == r.source_block_digest is not None
    (tmp_path / "cut.warc").write_bytes(b"WARC/1.0\r\nWARC-Type: response\r\nContent-Length: 99\r\n\r\nHTTP/1.1 200 OK\r\n\r\nabc")
    r = warc.read_warc(spark, str(tmp_path / "cut.warc")).first()
    assert r.truncated and bytes(r.payload) == b"abc"


def test_warc_edges(spark):
    import gzip

    one = lambda raw, head, **more: warc.derive(spark.createDataFrame([{"record_id": "r", "target_uri": "u", "warc_date": "d", "http_headers": head, "payload": raw, **more}])).where("warc_type = 'conversion'").first()
    text = "<p>gr\u00fc\u00df dich</p>"
    packed = gzip.compress(text.encode())
    assert one(packed, "HTTP/1.1 200 OK\r\nContent-Encoding: gzip\r\n").block == "gr\u00fc\u00df dich"
    chunked = b"".join(b"%x\r\n%s\r\n" % (len(x), x) for x in (packed[:7], packed[7:])) + b"0\r\n\r\n"
    r = one(chunked, "HTTP/1.1 200 OK\r\ncontent-encoding: gzip\r\ntransfer-encoding: chunked\r\n", payload_digest="sha1:KNOWN", block_digest="sha1:BLOCK")
    assert (r.block, r.source_payload_digest, r.source_block_digest) == ("gr\u00fc\u00df dich", "sha1:KNOWN", "sha1:BLOCK")
    assert one(text.encode("latin-1"), "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=ISO-8859-1\r\n").block == "gr\u00fc\u00df dich"
    assert one(b"not packed", "Content-Encoding: gzip\r\n").block == "not packed" and one(b"\xff", "Content-Type: x; charset=nonsense").block == "\ufffd"
    pages = spark.createDataFrame([(1, "u", "<p>a</p>" * 20000, "x"), (1, "u", "<p>a</p>" * 20000, "x"), (None, None, None, None)], "page_id long, url string, html string, record_id string")
    got = warc.report(pages).collect()
    assert len(got) == 6 and len({r.record_id for r in got}) == 4 and max(r.content_length for r in got) >= 39999
    assert warc.report(pages.limit(0)).count() == 0


def test_embeddings_without_ids_and_with_clashing_names(spark):
    rows = [(None, [1.0, 0.0], 1, "a"), (None, [1.0, 0.0], 1, "b"), (1, [1.0, 0.01], 1, "c"), (2, [1.0, 0.0], 1, "d"), (2, [1.0, 0.0], 1, "e"), (3, [0.0, 1.0], 2, "f")]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, keep string")
    got = sorted(((r.vec_id, r.n_links, r.component_id, r.kept) for r in embeddings.groups(df).collect()), key=repr)
    assert got == sorted([(None, 0, None, True)] * 2 + [(1, 2, 1, True)] + [(2, 2, 1, False)] * 2 + [(3, 0, 3, True)], key=repr)
    kept = embeddings.keep_representatives(df)
    assert kept.columns == df.columns and {r.keep for r in kept.collect()} == {"a", "b", "c", "f"}


def test_embeddings(spark):
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(12, 8))
    rows = []
    for i in range(400):
        c = centres[i % 12] + rng.normal(size=8) * 0.12
        rows.append((i, [float(x) for x in c], int(i % 3)))
    rows += [(1000 + k, rows[5][1], rows[5][2]) for k in range(40)]
    rows += [(2000, None, 1), (2001, [0.0] * 8, 1), (2002, [float("nan")] * 8, 1), (2003, rows[0][1], None), (2004, [None] + [1.0] * 7, 1), (2005, [1.0, 2.0], 0), (2006, [2.0, 4.0], 0), (2007, [], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    ok = [(i, np.array(x), y) for i, x, y in rows if x and y is not None and None not in x and np.isfinite(x).all() and np.any(x)]
    links = {i: [j for j, b, z in ok if j != i and y == z and len(a) == len(b) and a @ b / np.linalg.norm(a) / np.linalg.norm(b) >= 0.93] for i, a, y in ok}
    root = {i: i for i, *_ in rows}
    changed = True
    while changed:
        changed = False
        for i, js in links.items():
            low = min([root[i], *(root[j] for j in js)])
            for j in (i, *js):
                if root[j] != low:
                    root[j], changed = low, True
    for cell in (4096, 20):  # one cell for each label; many cells with guests
        got = {r.vec_id: r for r in embeddings.groups(df, cell_rows=cell).collect()}
        assert len(got) == len(rows)
        for i, *_ in rows:
            assert (got[i].n_links, got[i].component_id, got[i].kept) == (len(links.get(i, ())), root[i], root[i] == i)
    assert embeddings.groups(df.limit(0)).count() == 0
    assert embeddings.keep_representatives(df).count() == len({v for v in root.values()})


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    out = corpus_pipeline.run(spark, sf)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert out.count() <= docs.count() and set(docs.columns) <= set(out.columns)
    assert out.where("decoded != text").count() == 0
    assert out.where(F.length("text") != F.col("n_chars")).count() == 0
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, before, sf)
        assert after.columns == docs.columns, name
        assert stage(spark, before.limit(0), sf).count() == 0, name
        before = after


def first_come(sets, least=0.8):
    """Numbers of the sets that stay when each one goes that is similar to an earlier one that stays."""
    stay = []
    for i, a in enumerate(sets):
        if not any((not a and not sets[j]) or (a | sets[j] and len(a & sets[j]) / len(a | sets[j]) >= least) for j in stay):
            stay.append(i)
    return set(stay)


def five_words(text):
    w = split(lower(text))
    return set(tuple(w[i : i + 5]) for i in range(len(w) - 4)) or ({tuple(w)} if w else set())


def test_keep_first_meets_every_similar_pair(spark):
    rng = random.Random(5)
    rows = []
    for _ in range(25):
        base = [rng.choice(WORDS) for _ in range(rng.randint(60, 300))]
        for _ in range(5):
            t = list(base)
            for k in range(rng.randint(0, len(t) // 40)):
                t[rng.randrange(len(t))] = f"new{k}{rng.random()}"
            rows.append(" ".join(t))
    rng.shuffle(rows)
    sets = [five_words(t) for t in rows]
    near = [(i, j) for j in range(len(rows)) for i in range(j) if len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8]
    fp = simhash.fingerprints_of(pa.array(rows), 5)
    assert any(bin(int(fp[i] ^ fp[j])).count("1") > 8 for i, j in near)
    docs = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    texts = docs.withColumnRenamed("doc_id", "id")
    left = write_table(simhash.shared_prefixes(texts, 5, 0.8))[0]
    met = {(r.a, r.b) for r in simhash.candidates(left, 1000, 0.8).where("a IS NOT NULL").collect()}
    assert {(i, j) for i, j in near if sets[i] != sets[j]} <= met
    assert {r.doc_id for r in simhash.keep_first(docs).collect()} == first_come(sets)


def test_keep_first_settles_many_groups_of_one_template(spark):
    rng = random.Random(6)
    word = lambda: f"t{rng.randrange(10**6)}"
    common = [word() for _ in range(258)]
    rows = []
    for _ in range(64):
        t = common + [word() for _ in range(42)]
        rows += [" ".join(t), " ".join([*t[:-1], "other"])]
    sets = [five_words(t) for t in rows]
    want = first_come(sets)
    assert len(want) == 64
    got = simhash.keep_first(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string"))
    assert {r.doc_id for r in got.collect()} == want
    # A chain: every second document goes, one after the other.
    long = [word() for _ in range(900)]
    chain = [" ".join(long[20 * i : 20 * i + 200]) for i in range(30)]
    got = simhash.keep_first(spark.createDataFrame(list(enumerate(chain)), "doc_id long, text string"))
    assert {r.doc_id for r in got.collect()} == first_come([five_words(t) for t in chain]) == set(range(0, 30, 2))


def test_pieces_have_log_scores(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").unionByName(spark.createDataFrame([(-1, "the house is information"), (-2, None), (-3, "")], "doc_id long, text string"))
    m = pieces.fit(docs).value
    assert np.exp(m.scores[m.ids]).sum() == pytest.approx(1, abs=1e-3)
    old = pieces.load(spark).value
    new, at = m.encode(pa.array(["the house is information"]))
    assert len(new) < len(old.encode(pa.array(["the house is information"]))[0])
    assert m.pieces[new[0]] == "▁the"
    # Expected uses and likelihood against all segmentations.
    text = " theand"
    score = {m.pieces[i].replace("▁", " "): m.scores[i] for i in m.ids}

    def ways(t):
        return [[t[:k], *w] for k in range(1, len(t) + 1) if t[:k] in score for w in ways(t[k:])] if t else [[]]

    p = [np.exp(sum(score[x] for x in w)) for w in ways(text)]
    use, likelihood = m.expected(np.frombuffer(text.encode() + bytes(8), np.uint8), np.array([0]), np.array([len(text)]), np.array([3]))
    assert likelihood == pytest.approx(3 * np.log(sum(p)))
    for i in np.flatnonzero(use):
        x = m.pieces[i].replace("▁", " ")
        assert use[i] == pytest.approx(3 * sum(q * w.count(x) for q, w in zip(p, ways(text))) / sum(p))
    # The same by logs, where products would vanish.
    far = m.scored(np.where(np.arange(len(m.scores)) == m.ids[-1], -1000.0, m.scores))
    both = far.expected(np.frombuffer(text.encode() + bytes(8), np.uint8), np.array([0]), np.array([len(text)]), np.array([3]))
    assert both[1] == pytest.approx(likelihood) and both[0] == pytest.approx(use)
    assert pieces.fit(docs.limit(0)).value.encode(pa.array(["a b"]))[1][-1] > 0


def test_pieces_equal_the_library_under_the_same_scores(spark):
    """The fitted scores in a unigram model file, read by the library: the same pieces, or others that score no better."""
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2 as pb

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    m = pieces.fit(docs).value
    proto = pb.ModelProto()
    with open(pieces.DEFAULT_MODEL, "rb") as f:
        proto.ParseFromString(f.read())
    for p, x in zip(proto.pieces, m.scores):
        p.score = float(x)
    proto.trainer_spec.model_type = 1
    library = sentencepiece.SentencePieceProcessor(model_proto=proto.SerializeToString())
    texts = [r.text for r in docs.collect() if r.text and "  " not in r.text and "\n" not in r.text.strip() and r.text == r.text.strip()][:60]
    texts = [" ".join(t.split()[:40]) for t in texts]
    ids, at = m.encode(pa.array(texts))
    same = 0
    for t, i, j in zip(texts, at[:-1], at[1:]):
        own, theirs = ids[i:j].tolist(), library.encode(t)
        same += own == theirs
        if library.decode(theirs) == t and not set(own) & set(m.byte_id.tolist()):
            assert sum(m.scores[own]) >= sum(m.scores[theirs]) - 1e-3
    assert len(texts) >= 20 and same >= 0.9 * len(texts)


def test_keep_first_links_by_fingerprints(spark, monkeypatch):
    rng = random.Random(8)
    base = [f"w{rng.randrange(10**6)}" for _ in range(600)]
    rows = [" ".join(base), " ".join([*base[:-1], "other"]), " ".join(f"v{rng.randrange(10**6)}" for _ in range(50))]
    # Without fingerprints that meet, rare shingles still find the pair; with them, it is judged once.
    judged, similar = [], simhash.similar

    def watched(pairs, *rest):
        judged.append([(r.a, r.b) for r in pairs.collect()])
        return similar(pairs, *rest)

    monkeypatch.setattr(simhash, "similar", watched)
    docs = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.keep_first(docs).collect()) == [0, 2]
    assert judged[0] == [(0, 1)] and not any(judged[1:])
    judged.clear()
    monkeypatch.setattr(simhash, "fingerprint_pairs", lambda texts, *rest: spark.createDataFrame([], "a long, b long"))
    assert sorted(r.doc_id for r in simhash.keep_first(docs).collect()) == [0, 2]
    assert not judged[0] and judged[1] == [(0, 1)]
