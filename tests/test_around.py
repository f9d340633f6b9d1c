"""Placement, comparators, files, SQL, streams, and the registered queries."""

import os
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.operators import balance, bounds, comparators
from copath.plans import sql
from copath.plans.miner import mine_rules
from copath.sources import files
from copath.sources.graphs import PropertyGraph, toy
from copath.streaming import edges as stream

SF = "/root/testdata/sf0.001"


def test_greedy_placement():
    rng = random.Random(3)
    for _ in range(30):
        n, parts = rng.randint(1, 60), rng.randint(1, 7)
        costs = [rng.choice((0, 0, 1, 2, 3, 7, 50)) for _ in range(n)]
        own = balance.greedy_by_vertex(costs, parts)
        want, held = [0] * parts, [0] * parts
        for i, p in own:
            want[p] += costs[i]
            held[p] += 1
        hist = {c: costs.count(c) for c in costs}
        runs = balance.greedy_by_cost(list(hist.items()), parts)
        got, size = [0] * parts, [0] * parts
        for c, lo, hi, p in runs:
            got[p] += c * (hi - lo + 1)
            size[p] += hi - lo + 1
        assert sorted(got) == sorted(want)
        assert sum(size) == n and max(size) <= -(-n // parts) and max(held) <= -(-n // parts)


def test_cost_and_plans(spark):
    g = toy(spark)
    costs = balance.vertex_cost(g, bounds.target_tables(g, 1))
    assert {r.v: r.cost for r in costs.collect()} == {1: 0, 2: 0, 3: 1, 4: 1, 5: 1, 6: 1, 7: 4, 8: 6, 9: 4, 10: 2, 11: 4, 12: 2}
    for how in (balance.balance_greedy, balance.balance_hash, balance.balance_snake):
        plan = how(costs, 3)
        assert plan.count() == 12
        r = balance.balance_report(plan).first()
        assert r.mean_load * r.n_parts == pytest.approx(26)
    assert balance.balance_report(balance.balance_greedy(costs, 2)).first().max_load == 13
    placed = balance.place(g.vertices, balance.balance_greedy(costs, 3), 3)
    assert placed.rdd.getNumPartitions() == 3 and placed.count() == 12


def test_correlated_pairs(spark):
    g = toy(spark)
    top = comparators.correlated_pairs(g, 2, 5).collect()
    assert len(top) == 5 and all(a.correlation >= b.correlation for a, b in zip(top, top[1:]))
    wide = comparators.correlated_pairs(g, 2, 5, h=1).collect()
    assert wide[0].correlation >= top[0].correlation


def test_files_and_sql(spark, tmp_path):
    g = toy(spark)
    r = mine_rules(g, MinerConfig(theta=2, max_len=1))
    for kind in ("parquet", "json", "csv"):
        files.write_result(r, str(tmp_path / kind), kind)
        assert spark.read.format(kind).option("header", False).load(str(tmp_path / kind / "rules")).count() == 2 * r.pairs.count()
    g.save(str(tmp_path / "g"))
    again = PropertyGraph.load(spark, str(tmp_path / "g"))
    assert again.items == g.items and again.labels == g.labels and again.edges.count() == 15
    (tmp_path / "e.csv").write_text("1,l,2\n2,l,3\n")
    assert files.read_edges(spark, str(tmp_path / "e.csv")).count() == 2
    (tmp_path / "t.nt").write_text('<http://x/a> <http://x/knows> <http://x/b> .\n<http://x/a> <http://x/job> "art\\"s" .\nnot a triple\n')
    v, a, e = files.read_triples(spark, str(tmp_path / "t.nt"))
    assert (v.count(), a.count(), e.count()) == (2, 1, 1)
    sql.register(spark, r)
    assert spark.sql("SELECT count(*) FROM patterns WHERE is_unit(pattern)").first()[0] == sum(p.unit for p in r.catalogue.support)
    assert spark.sql("SELECT covers(array(1, 2), array(2))").first()[0]
    assert spark.sql("SELECT count(*) FROM (SELECT array(1, 2, 3) AS a) AS t, LATERAL subsets(a, 2)").first()[0] == 6
    assert spark.sql("SELECT count(*) FROM rules").first()[0] == 2 * r.pairs.count()


def test_streams(spark, tmp_path):
    schema = "event_id long, ts timestamp, user_id long, event_type string"
    rows = [(i, f"2024-01-01 {i // 60:02d}:{i % 60:02d}:00", i % 3, "ab"[i % 2]) for i in range(0, 600, 5)]
    # Files out of order within the watermark; at last an event far ahead that lets the others go, and one that is too late.
    late = [(1000, "2024-01-01 00:01:00", 7, "a")]
    swapped = rows[:60]
    swapped[55:60], held = [], swapped[55:60]
    for k, part in enumerate((swapped, rows[60:66], held + rows[66:], [(2000, "2024-01-03 00:00:00", 9, "a")], late)):
        spark.createDataFrame(part, "event_id long, ts string, user_id long, event_type string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(str(tmp_path / f"in{k}"))
    src = str(tmp_path / "in")
    os.makedirs(src)
    events = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(src)

    def feed(k):
        for f in (tmp_path / f"in{k}").glob("part-*.parquet"):
            os.link(f, f"{src}/{k}-{f.name}")

    edges = stream.next_edges(events).writeStream.format("memory").queryName("next_edges").outputMode("append").option("checkpointLocation", str(tmp_path / "c1")).start()
    counts = stream.unit_support(events, "1 hour").writeStream.format("memory").queryName("supports").outputMode("append").option("checkpointLocation", str(tmp_path / "c2")).start()
    try:
        for k in range(5):
            feed(k)
            edges.processAllAvailable()
            counts.processAllAvailable()
        got = {(r.src, r.dst) for r in spark.table("next_edges").collect()}
        assert got == {(a, b) for u in range(3) for own in [[r[0] for r in rows if r[2] == u]] for a, b in zip(own, own[1:])}
        first = spark.table("supports").where("window_start = '2024-01-01 00:00:00'").collect()
        assert {r.pattern: r.support for r in first} == {"{type:a}": 3, "{type:b}": 3}
    finally:
        edges.stop()
        counts.stop()
    batch = stream.sessions(spark.read.parquet(str(tmp_path / "in0")), "16 minutes", None)
    assert batch.count() == 3


def test_entry_without_the_training_data_operators(tmp_path):
    """The two folders and the pipeline deleted: everything else is there and runs."""
    import shutil
    import subprocess
    import sys

    here = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(os.path.join(here, "copath"), tmp_path / "copath", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(os.path.join(here, "__spark_entry__.py"), tmp_path)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert 'rules_trade' in q and set(o) <= set(q) and not [k for k in q if k.startswith('op') or k == 'pipeline']"
    for with_pipeline in (False, True):
        if with_pipeline and os.path.exists(os.path.join(here, "corpus_pipeline.py")):
            shutil.copy(os.path.join(here, "corpus_pipeline.py"), tmp_path)
        done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={**os.environ, "PYTHONPATH": ""}, capture_output=True, text=True)
        assert done.returncode == 0, done.stderr


def test_sql_functions_and_json(spark, tmp_path):
    from copath.config import MinerConfig
    from copath.functions import measures
    from copath.operators import accuracy, sketches
    from copath.plans import sql
    from copath.plans.miner import mine_rules
    from copath.sources import files, graphs

    g = graphs.from_rows(spark, range(40), [(v, x) for v in range(40) for x in (["a,b", "c|d"] if v % 2 else ["a,b"])], [(v, "l*", (v + 1) % 40) for v in range(40)])
    r = mine_rules(g, MinerConfig(theta=5))
    sql.register(spark, r)
    args = "(SELECT array_agg(name) FROM (SELECT name FROM g_items ORDER BY item)), (SELECT array_agg(name) FROM (SELECT name FROM g_labels ORDER BY label))"
    assert spark.sql(f"SELECT text FROM patterns WHERE text != pattern_text(pattern, {args})").count() == 0
    names = r.catalogue.names
    got = {(x.p, x.q) for x in spark.sql("SELECT a.pid AS p, b.pid AS q FROM patterns AS a JOIN patterns AS b ON dominates(a.pattern, b.pattern)").collect()}
    assert got == {(i, j) for i, p in enumerate(names) for j, q in enumerate(names) if p.dominates(q) and p in r.catalogue.support and q in r.catalogue.support}
    assert spark.sql("SELECT gini(x) AS g FROM VALUES (0.0), (0.0), (0.0), (4.0) AS t(x)").first().g == pytest.approx(0.75)
    assert spark.sql("SELECT gini(x) AS g FROM VALUES (2.0), (2.0) AS t(x)").first().g == pytest.approx(0)
    assert spark.sql("SELECT count(*) AS n FROM (SELECT DISTINCT pattern.head AS h FROM patterns) AS p, LATERAL subsets(p.h, 2)").first().n > 0
    files.rules_as_json(r).coalesce(1).write.text(str(tmp_path / "rules"))
    back = files.read_rules_json(spark, str(tmp_path / "rules"))
    rules = r.rules()
    assert back.count() == rules.count() and back.agg(F.round(F.sum(back.measures["confidence"]), 6)).first()[0] == rules.agg(F.round(F.sum("confidence"), 6)).first()[0]
    best = measures.best_consequents(rules, rules, 2)
    assert best.count() == sum(min(2, n) for n in (x["count"] for x in rules.groupBy("x").count().collect()))
    fewer = rules.where("confidence >= 0.9")
    sides = {x.side: x["count"] for x in accuracy.differences(rules, fewer).groupBy("side").count().collect()}
    assert sides == {"missed": rules.count() - fewer.count(), "kept": fewer.count()}
    n = {(x.x, x.y): x.n for x in r.pairs.collect()}
    support = {r.catalogue.ids[p]: k for p, k in r.catalogue.support.items()}
    assert all(x.n == support[x.x] + support[x.y] - n[x.x, x.y] for x in sketches.either_support(r.matches, r.pairs).collect())
    assert all(abs(x.estimate - n[x.x, x.y]) < 1 for x in sketches.sketched_support(r.matches, r.pairs).collect())


def test_hashed_neighbours(spark):
    from copath.sources import graphs

    sf = "/root/testdata/sf0.001"
    v = {r.vec_id: r for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect() if r.embedding and any(r.embedding)}
    unit = {k: [x / sum(y * y for y in r.embedding) ** 0.5 for x in r.embedding] for k, r in v.items()}
    cos = lambda a, b: sum(x * y for x, y in zip(unit[a], unit[b]))
    got = graphs.lsh_neighbours(spark, sf, 3).collect()
    near = {(r.src, r.dst) for r in got}
    assert all(r.sim == pytest.approx(cos(r.src, r.dst), abs=1e-6) for r in got[:200])
    some = sorted(v)[:60]
    want = {(a, b) for a in some for b in sorted((x for x in v if x != a), key=lambda x: (-cos(a, x), x))[:3] if cos(a, b) >= 0.5}
    assert len(want & near) >= 0.9 * len(want)


@pytest.mark.parametrize("name", ["rules_trade", "rules_prefix_only_trade", "rules_lattice_trade", "rules_threshold_sampled_trade", "best_consequents_trade", "either_support_trade", "pattern_counts_trade", "rules_corpus", "reach4_eventchain", "multi_len2_trade", "sampled_support_trade", "rules_damped_lineage", "bias_segment_priority", "session_edges"])
def test_queries_equal_sql(spark, name):
    import __spark_entry__ as entry

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    df = entry.queries()[name](spark, SF)
    r = con.execute(entry.oracle_sql()[name])
    names = [x[0] for x in r.description]
    norm = lambda v: round(float(v), 5) if isinstance(v, (int, float)) and not isinstance(v, bool) else v
    want = sorted((tuple(norm(v) for _, v in sorted(zip(names, row))) for row in r.fetchall()), key=repr)
    got = sorted((tuple(norm(v) for _, v in sorted(row.asDict().items())) for row in df.collect()), key=repr)
    assert got == want and sorted(names) == sorted(df.columns)


def test_graphs_from_tables_by_plain_loops(spark):
    """Edges that the shared SQL builds through slices, against sorted lists."""
    from copath.sources import graphs

    g = graphs.build(spark, SF, "corpus")
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "source", F.md5("text").alias("h")).collect()
    by = {}
    for r in sorted(docs, key=lambda r: r.doc_id):
        by.setdefault(r.source, []).append(r.doc_id * 16 + 9)
    want = {(a, "next_in_source", b) for own in by.values() for a, b in zip(own, own[1:])}
    same = {}
    for r in docs:
        if r.h is not None:
            same.setdefault(r.h, []).append(r.doc_id * 16 + 9)
    for own in same.values():
        want |= {x for v in own if v != min(own) for x in ((v, "same_text", min(own)), (min(own), "same_text", v))}
    assert {(e.src, g.labels[e.label], e.dst) for e in g.edges.collect()} == want
    g = graphs.build(spark, SF, "users")
    events = sorted((r.ts, r.event_id, r.user_id, r.event_type) for r in spark.read.parquet(f"{SF}/events.parquet").select("ts", "event_id", "user_id", "event_type").collect())
    assert {(e.src, g.labels[e.label], e.dst) for e in g.edges.collect()} == {(a[2] * 16 + 7, a[3], b[2] * 16 + 7) for a, b in zip(events, events[1:])}
