"""Property graphs: the data model, and graphs built from tables.

Graphs that SQL can express are written once as SQL over ``{table}`` placeholders that both Spark and
DuckDB read; a vertex id is its table's key times 16 plus a code of its kind.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from copath.plans.meter import together
from copath.plans.store import cut, freed

#: Vocabularies up to this size are joined by broadcast; larger ones by shuffle.
BROADCAST_NAMES = 500_000


@dataclass
class PropertyGraph:
    """vertices(v), attrs(v, item), edges(src, label, dst): distinct rows; items and labels are numbered in byte order of their names."""

    vertices: DataFrame
    attrs: DataFrame
    edges: DataFrame
    items: list[str] = field(default_factory=list)
    labels: list[str] = field(default_factory=list)
    _n: int | None = None
    #: Kinds of the vertices with all counts, if they were made before any run.
    kinds: object | None = None

    @property
    def n(self) -> int:
        if self._n is None:
            self._n = self.vertices.count()
        return self._n

    @staticmethod
    def encode(vertices: DataFrame, attrs: DataFrame, edges: DataFrame) -> PropertyGraph:
        """From frames with names: attrs(v, item string), edges(src, label string, dst). Rows with nulls say nothing and are dropped."""
        spark = vertices.sparkSession
        attrs, edges = attrs.dropna(), edges.dropna()

        def numbered(df: DataFrame, name: str) -> tuple[list[str], DataFrame]:
            names = sorted((r[0] for r in df.select(name).distinct().collect()), key=lambda s: s.encode())
            table = spark.createDataFrame([(i, s) for i, s in enumerate(names)], f"id int, {name} string")
            return names, F.broadcast(table) if len(names) <= BROADCAST_NAMES else table

        with freed(spark):
            (items, item_ids), (labels, label_ids) = together(lambda: numbered(attrs, "item"), lambda: numbered(edges, "label"))
            # Rows of one vertex lie together, so that counts by vertex shrink before they are shuffled; a vertex of very many edges has several ranges.
            coded = attrs.join(item_ids, "item").select("v", F.col("id").alias("item")).repartition("v").distinct()
            steps = edges.join(label_ids, "label").select("src", F.col("id").alias("label"), "dst").repartitionByRange("src", "dst").distinct()
            tables = together(*[lambda df=df: cut(df) for df in (vertices.select("v").dropna().distinct(), coded, steps)])
        return PropertyGraph(*tables, items, labels)

    def attr_sets(self) -> DataFrame:
        """(v, items): sorted item array of each vertex that has items."""
        return self.attrs.groupBy("v").agg(F.sort_array(F.collect_set("item")).alias("items"))

    def save(self, path: str) -> None:
        """Three Parquet tables with names; edges partitioned by label."""
        spark = self.vertices.sparkSession
        names = lambda xs, c: name_table(spark, c, xs)
        self.vertices.write.mode("overwrite").parquet(f"{path}/vertices")
        self.attrs.join(names(self.items, "item"), "item").select("v", F.col("name").alias("item")).write.mode("overwrite").parquet(f"{path}/attrs")
        self.edges.join(names(self.labels, "label"), "label").select("src", F.col("name").alias("label"), "dst").write.mode("overwrite").partitionBy("label").parquet(f"{path}/edges")

    @staticmethod
    def load(spark: SparkSession, path: str) -> PropertyGraph:
        read = lambda t: spark.read.parquet(f"{path}/{t}")
        return PropertyGraph.encode(read("vertices"), read("attrs"), read("edges").select("src", F.col("label").cast("string").alias("label"), "dst"))


def name_table(spark: SparkSession, column: str, names: list[str]) -> DataFrame:
    """(column, name) of a vocabulary; broadcast up to a checked size."""
    table = spark.createDataFrame(list(enumerate(names)), f"{column} int, name string")
    return F.broadcast(table) if len(names) <= BROADCAST_NAMES else table


def band(x: str) -> str:
    return f"CASE WHEN {x} < 0 THEN 'neg' WHEN {x} < 5000 THEN 'mid' ELSE 'high' END"


def chars(x: str) -> str:
    return f"CASE WHEN {x} < 500 THEN 'short' WHEN {x} < 3000 THEN 'medium' ELSE 'long' END"


def _union(*parts: str) -> str:
    return " UNION ALL ".join(parts)


_TRADE_V = _union(
    "SELECT c_custkey * 16 + 1 AS v FROM {customer}",
    "SELECT o_orderkey * 16 + 2 AS v FROM {orders}",
    "SELECT p_partkey * 16 + 3 AS v FROM {part}",
    "SELECT s_suppkey * 16 + 4 AS v FROM {supplier}",
    "SELECT CAST(n_nationkey AS BIGINT) * 16 + 5 AS v FROM {nation}",
    "SELECT CAST(r_regionkey AS BIGINT) * 16 + 6 AS v FROM {region}",
)
_TRADE_A = _union(
    "SELECT c_custkey * 16 + 1 AS v, 'kind:customer' AS item FROM {customer}",
    "SELECT c_custkey * 16 + 1 AS v, concat('seg:', c_mktsegment) AS item FROM {customer}",
    f"SELECT c_custkey * 16 + 1 AS v, concat('bal:', {band('c_acctbal')}) AS item FROM {{customer}}",
    "SELECT o_orderkey * 16 + 2 AS v, 'kind:order' AS item FROM {orders}",
    "SELECT o_orderkey * 16 + 2 AS v, concat('st:', o_orderstatus) AS item FROM {orders}",
    "SELECT o_orderkey * 16 + 2 AS v, concat('prio:', o_orderpriority) AS item FROM {orders}",
    "SELECT p_partkey * 16 + 3 AS v, 'kind:part' AS item FROM {part}",
    "SELECT p_partkey * 16 + 3 AS v, concat('brand:', p_brand) AS item FROM {part}",
    "SELECT p_partkey * 16 + 3 AS v, concat('type:', p_type) AS item FROM {part}",
    "SELECT s_suppkey * 16 + 4 AS v, 'kind:supplier' AS item FROM {supplier}",
    f"SELECT s_suppkey * 16 + 4 AS v, concat('bal:', {band('s_acctbal')}) AS item FROM {{supplier}}",
    "SELECT CAST(n_nationkey AS BIGINT) * 16 + 5 AS v, 'kind:nation' AS item FROM {nation}",
    "SELECT CAST(r_regionkey AS BIGINT) * 16 + 6 AS v, 'kind:region' AS item FROM {region}",
    "SELECT CAST(r_regionkey AS BIGINT) * 16 + 6 AS v, concat('region:', r_name) AS item FROM {region}",
)
_LOCATED = (
    "SELECT c_custkey * 16 + 1 AS src, 'located_in' AS label, CAST(c_nationkey AS BIGINT) * 16 + 5 AS dst FROM {customer}",
    "SELECT s_suppkey * 16 + 4 AS src, 'located_in' AS label, CAST(s_nationkey AS BIGINT) * 16 + 5 AS dst FROM {supplier}",
    "SELECT CAST(n_nationkey AS BIGINT) * 16 + 5 AS src, 'located_in' AS label, CAST(n_regionkey AS BIGINT) * 16 + 6 AS dst FROM {nation}",
)
_SHIPPED = "SELECT l_orderkey * 16 + 2 AS src, 'shipped_by' AS label, l_suppkey * 16 + 4 AS dst FROM {lineitem}"
#: The bands of a source's out-degree (fixed values): 1, 2-4, 5-14, 15-29, 30-49, 50-100, above.
DEGREE_BANDS = ((1, "1"), (4, "2_4"), (14, "5_14"), (29, "15_29"), (49, "30_49"), (100, "50_100"), (None, "over_100"))


def degree_band(x: str) -> str:
    return "CASE " + " ".join(f"WHEN {x} <= {hi} THEN '{name}'" for hi, name in DEGREE_BANDS if hi) + f" ELSE '{DEGREE_BANDS[-1][1]}' END"


#: Ids that one window sorts at most, of a source that may have any number.
_SLICE = "CAST(floor(doc_id / 65536) AS BIGINT)"
GRAPHS: dict[str, dict[str, str]] = {
    "trade": {
        "vertices": _TRADE_V,
        "attrs": _TRADE_A,
        "edges": _union(
            "SELECT o_custkey * 16 + 1 AS src, 'places' AS label, o_orderkey * 16 + 2 AS dst FROM {orders}",
            "SELECT l_orderkey * 16 + 2 AS src, 'contains' AS label, l_partkey * 16 + 3 AS dst FROM {lineitem}",
            _SHIPPED,
            *_LOCATED,
        ),
    },
    "lineage": {
        "vertices": _TRADE_V,
        "attrs": _TRADE_A,
        "edges": _union(
            f"SELECT o_custkey * 16 + 1 AS src, concat('places_', {degree_band('n')}) AS label, o_orderkey * 16 + 2 AS dst FROM {{orders}} JOIN (SELECT o_custkey AS k, count(*) AS n FROM {{orders}} GROUP BY o_custkey) AS d ON o_custkey = k",
            "SELECT l_orderkey * 16 + 2 AS src, concat('contains_', l_returnflag, l_linestatus, CAST(year(l_shipdate) AS VARCHAR(4))) AS label, l_partkey * 16 + 3 AS dst FROM {lineitem}",
            _SHIPPED,
            *_LOCATED,
        ),
    },
    "copart": {
        "vertices": "SELECT p_partkey * 16 + 3 AS v FROM {part}",
        "attrs": "SELECT p_partkey * 16 + 3 AS v, concat('type:', p_type) AS item FROM {part}",
        "edges": "SELECT a.l_partkey * 16 + 3 AS src, concat('with_', a.l_returnflag) AS label, b.l_partkey * 16 + 3 AS dst FROM {lineitem} AS a JOIN {lineitem} AS b ON a.l_orderkey = b.l_orderkey WHERE a.l_partkey <> b.l_partkey",
    },
    # The globally next event: within the hour by a window, across hours from each one's last to the next one's first.
    "users": {
        "vertices": "SELECT DISTINCT user_id * 16 + 7 AS v FROM {events}",
        "attrs": _union(
            "SELECT user_id * 16 + 7 AS v, concat('seg:', c_mktsegment) AS item FROM (SELECT DISTINCT user_id FROM {events}) AS u JOIN {customer} ON user_id = c_custkey",
            f"SELECT user_id * 16 + 7 AS v, concat('bal:', {band('c_acctbal')}) AS item FROM (SELECT DISTINCT user_id FROM {{events}}) AS u JOIN {{customer}} ON user_id = c_custkey",
            "SELECT user_id * 16 + 7 AS v, concat('reg:', r_name) AS item FROM (SELECT DISTINCT user_id FROM {events}) AS u JOIN {customer} ON user_id = c_custkey JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey",
        ),
        "edges": "SELECT user_id * 16 + 7 AS src, event_type AS label, coalesce(nxt, first_next) * 16 + 7 AS dst FROM (SELECT user_id, event_type, date_trunc('hour', ts) AS day, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS nxt FROM {events}) AS e JOIN (SELECT day AS d, lead(first_user) OVER (ORDER BY day) AS first_next FROM (SELECT date_trunc('hour', ts) AS day, user_id AS first_user, row_number() OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS k FROM {events}) AS f WHERE k = 1) AS g ON day = d WHERE coalesce(nxt, first_next) IS NOT NULL",
    },
    "eventchain": {
        "vertices": "SELECT event_id * 16 + 8 AS v FROM {events}",
        "attrs": _union(
            "SELECT event_id * 16 + 8 AS v, concat('type:', event_type) AS item FROM {events}",
            "SELECT event_id * 16 + 8 AS v, CASE WHEN hour(ts) < 6 THEN 'hour:0' WHEN hour(ts) < 12 THEN 'hour:1' WHEN hour(ts) < 18 THEN 'hour:2' ELSE 'hour:3' END AS item FROM {events}",
            "SELECT event_id * 16 + 8 AS v, CASE WHEN value < 20 THEN 'val:low' WHEN value < 80 THEN 'val:mid' ELSE 'val:high' END AS item FROM {events}",
        ),
        "edges": "SELECT src, label, dst FROM (SELECT event_id * 16 + 8 AS src, 'next' AS label, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) * 16 + 8 AS dst FROM {events}) AS e WHERE dst IS NOT NULL",
    },
    "corpus": {
        "vertices": "SELECT doc_id * 16 + 9 AS v FROM {documents}",
        "attrs": _union(
            "SELECT doc_id * 16 + 9 AS v, concat('lang:', lang) AS item FROM {documents}",
            "SELECT doc_id * 16 + 9 AS v, concat('src:', source) AS item FROM {documents}",
            f"SELECT doc_id * 16 + 9 AS v, concat('len:', {chars('n_chars')}) AS item FROM {{documents}}",
            "SELECT doc_id * 16 + 9 AS v, CASE WHEN quality = 1 THEN 'quality:1' ELSE 'quality:0' END AS item FROM {labels}",
            "SELECT doc_id * 16 + 9 AS v, CASE WHEN toxic = 1 THEN 'toxic:1' ELSE 'toxic:0' END AS item FROM {labels}",
        ),
        "edges": _union(
            # Copies meet in a star around the smallest id and back, so that a group of n copies has 2n edges, not n squared.
            "SELECT doc_id * 16 + 9 AS src, 'same_text' AS label, head * 16 + 9 AS dst FROM (SELECT doc_id, head FROM {documents} JOIN (SELECT md5(text) AS h, min(doc_id) AS head FROM {documents} WHERE text IS NOT NULL GROUP BY md5(text)) AS m ON md5(text) = h) AS t WHERE doc_id <> head",
            "SELECT head * 16 + 9 AS src, 'same_text' AS label, doc_id * 16 + 9 AS dst FROM (SELECT doc_id, head FROM {documents} JOIN (SELECT md5(text) AS h, min(doc_id) AS head FROM {documents} WHERE text IS NOT NULL GROUP BY md5(text)) AS m ON md5(text) = h) AS t WHERE doc_id <> head",
            # The next document of a source: within a slice of ids by a window, across slices from each one's last to the next one's first.
            f"SELECT src, label, dst FROM (SELECT doc_id * 16 + 9 AS src, 'next_in_source' AS label, coalesce(nxt, first_next) * 16 + 9 AS dst FROM (SELECT doc_id, source, {_SLICE} AS sl, lead(doc_id) OVER (PARTITION BY source, {_SLICE} ORDER BY doc_id) AS nxt FROM {{documents}}) AS d JOIN (SELECT source AS s2, sl2, lead(first_id) OVER (PARTITION BY source ORDER BY sl2) AS first_next FROM (SELECT source, {_SLICE} AS sl2, min(doc_id) AS first_id FROM {{documents}} WHERE doc_id IS NOT NULL GROUP BY source, {_SLICE}) AS f) AS g ON source IS NOT DISTINCT FROM s2 AND sl = sl2) AS e WHERE dst IS NOT NULL",
        ),
    },
    "dialog": {
        "vertices": "SELECT (conv_id * 4096 + turn) * 16 + 10 AS v FROM {conversations}",
        "attrs": _union(
            "SELECT (conv_id * 4096 + turn) * 16 + 10 AS v, concat('role:', role) AS item FROM {conversations}",
            "SELECT (conv_id * 4096 + turn) * 16 + 10 AS v, CASE WHEN length(text) < 200 THEN 'len:short' WHEN length(text) < 800 THEN 'len:medium' ELSE 'len:long' END AS item FROM {conversations}",
        ),
        "edges": "SELECT src, label, dst FROM (SELECT (conv_id * 4096 + turn) * 16 + 10 AS src, 'reply' AS label, lead((conv_id * 4096 + turn) * 16 + 10) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM {conversations}) AS e WHERE dst IS NOT NULL",
    },
}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def from_sql(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    """One of GRAPHS over a folder of tables."""
    parts = GRAPHS[name]
    used = [t for t in TABLES if any(f"{{{t}}}" in s for s in parts.values())]
    frames = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in used}
    run = lambda s: spark.sql(s, **{t: frames[t] for t in used if f"{{{t}}}" in s})
    return PropertyGraph.encode(*(run(parts[k]) for k in ("vertices", "attrs", "edges")))


def oracle_graph(name: str) -> str:
    """The same graph as common table expressions vs(v), ats(v, item), es(src, label, dst) for plain SQL."""
    plain = lambda s: s.format(**{t: t for t in TABLES})
    g = GRAPHS[name]
    return f"WITH vs AS (SELECT DISTINCT v FROM ({plain(g['vertices'])}) AS x), ats AS (SELECT DISTINCT v, item FROM ({plain(g['attrs'])}) AS x), es AS (SELECT DISTINCT src, label, dst FROM ({plain(g['edges'])}) AS x)"


def web(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Pages and the targets of their links."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("url", "html")
    key = lambda c: (F.xxhash64(c).bitwiseAND(F.lit((1 << 58) - 1)) * 16 + 11)
    links = pages.select(key("url").alias("src"), F.explode(F.expr("""regexp_extract_all(html, 'href="([^"]*)"', 1)""")).alias("href"))
    host = F.regexp_extract("url", r"^https?://([^/?#]+)", 1)
    p = pages.select(key("url").alias("v"), "url", F.regexp_extract("html", r'<html[^>]*lang="([^"]+)"', 1).alias("lang"), F.element_at(F.split(host, r"\."), -1).alias("tld"), F.regexp_extract("url", "^([a-z]+):", 1).alias("scheme"))
    some = lambda c, name: p.where(F.col(c) != "").select("v", F.concat(F.lit(f"{name}:"), c).alias("item"))
    attrs = p.select("v", F.lit("kind:page").alias("item")).union(some("lang", "lang")).union(some("tld", "tld")).union(some("scheme", "scheme")).union(links.select(key("href").alias("v"), F.lit("kind:link").alias("item")))
    edges = links.select("src", F.lit("links_to").alias("label"), key("href").alias("dst"))
    return PropertyGraph.encode(p.select("v").union(links.select(key("href").alias("v"))), attrs, edges)


def vecnn(spark: SparkSession, sf_dir: str, neighbours: int = 5, one_label: bool = False, block: int = 1024) -> PropertyGraph:
    """Vectors and their nearest neighbours by cosine (ties: smaller id). Exact, block against block; each block pair keeps its best only."""
    import numpy as np
    import pyarrow as pa

    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding", "label")
    n = max(1, -(-rows.count() // block))
    part = rows.select("vec_id", "embedding", F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int").alias("b"))
    other = F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = part.select("vec_id", "embedding", F.col("b").alias("i"), other.alias("j"), F.lit(True).alias("own"))
    right = part.select("vec_id", "embedding", other.alias("i"), F.col("b").alias("j"), F.lit(False).alias("own"))

    def best(t: pa.Table) -> pa.Table:
        own, ids = t.column("own").to_numpy(), t.column("vec_id").to_numpy()
        x = np.stack(t.column("embedding").to_pandas()).astype(np.float64)
        x /= np.maximum(np.sqrt((x * x).sum(1, keepdims=True)), 1e-300)
        a, b = np.flatnonzero(own), np.flatnonzero(~own)
        if not len(a) or not len(b):
            return pa.table({"src": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "sim": pa.array([], pa.float64())})
        sim = np.where(ids[a][:, None] == ids[b][None], -np.inf, x[a] @ x[b].T)
        order = np.lexsort((np.broadcast_to(ids[b], sim.shape), -sim), axis=1)[:, :neighbours]
        src, dst, s = np.repeat(ids[a], order.shape[1]), ids[b][order].ravel(), np.take_along_axis(sim, order, 1).ravel()
        ok = np.isfinite(s)
        return pa.table({"src": src[ok], "dst": dst[ok], "sim": s[ok]})

    from pyspark.sql import Window

    near = left.unionByName(right).groupBy("i", "j").applyInArrow(best, "src long, dst long, sim double")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), "dst"))
    near = near.withColumn("r", rank).where(F.col("r") <= neighbours)
    name = F.lit("near") if one_label else F.concat(F.lit("near_"), F.col("r").cast("string"))
    key = lambda c: F.col(c) * 16 + 12
    attrs = rows.where("label IS NOT NULL").select(key("vec_id").alias("v"), F.concat(F.lit("label:"), F.col("label").cast("string")).alias("item"))
    return PropertyGraph.encode(rows.select(key("vec_id").alias("v")), attrs, near.select(key("src").alias("src"), name.alias("label"), key("dst").alias("dst")))


def lsh_neighbours(spark: SparkSession, sf_dir: str, neighbours: int = 5, least: float = 0.5, bucket: float = 0.5, tables: int = 8) -> DataFrame:
    """src, dst, sim: nearest neighbours of cosine ``least`` or more among vectors that meet in a hash table of random projections.

    For tables of vectors too large for all blocks; what it misses, ``vecnn`` finds. Equal vectors always meet.
    """
    from pyspark.ml.feature import BucketedRandomProjectionLSH, Normalizer
    from pyspark.ml.functions import array_to_vector
    from pyspark.sql import Window

    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").where("embedding IS NOT NULL AND exists(embedding, x -> x != 0)")
    unit = Normalizer(inputCol="raw", outputCol="unit").transform(rows.select("vec_id", array_to_vector(F.col("embedding").cast("array<double>")).alias("raw")))
    model = BucketedRandomProjectionLSH(inputCol="unit", outputCol="hashes", bucketLength=bucket, numHashTables=tables, seed=42).fit(unit)
    # On unit vectors, a distance is a cosine.
    near = model.approxSimilarityJoin(unit, unit, (2 - 2 * least) ** 0.5, "d").where("datasetA.vec_id != datasetB.vec_id")
    pairs = near.select(F.col("datasetA.vec_id").alias("src"), F.col("datasetB.vec_id").alias("dst"), (1 - F.col("d") * F.col("d") / 2).alias("sim"))
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), "dst"))
    return pairs.withColumn("r", rank).where(F.col("r") <= neighbours).drop("r")


def generated(spark: SparkSession, n: int, kind: str = "uniform", degree: int = 5, labels: int = 500, items: int = 500, items_each: int = 2, seed: int = 42) -> PropertyGraph:
    """n vertices with ``degree`` edges on average; end points drawn evenly or by an exponential law. Every draw is a hash, so it repeats on any cluster."""
    even = lambda *c: F.pmod(F.xxhash64(*c, F.lit(seed)), F.lit(1 << 30)) / float(1 << 30)
    v = spark.range(n).withColumnRenamed("id", "v")
    attrs = v.select("v", F.explode(F.sequence(F.lit(1), F.lit(items_each))).alias("k")).select("v", F.concat(F.lit("a"), F.floor(even("v", "k", F.lit("item")) * items).cast("string")).alias("item"))
    e = spark.range(n * degree)
    u = even("id", F.lit("dst"))
    dst = F.floor(u * n) if kind == "uniform" else F.pmod(F.floor(-F.log(1 - u) * (n / 10.0)), F.lit(n))
    edges = e.select(F.floor(even("id", F.lit("src")) * n).cast("long").alias("src"), F.concat(F.lit("l"), F.floor(even("id", F.lit("label")) * labels).cast("string")).alias("label"), dst.cast("long").alias("dst"))
    return PropertyGraph.encode(v, attrs, edges)


#: A 12-vertex example: items of each vertex, and edges.
TOY_ITEMS = {1: "City", 2: "City", 3: "Museum", 4: "Museum", 5: "Uni", 6: "Uni", 7: "Art Female", 8: "CS Male", 9: "CS Male", 10: "Art Male", 11: "Chem Female", 12: "Chem Male"}
TOY_EDGES = "3 LocatedIn 1; 4 LocatedIn 2; 5 LocatedIn 2; 6 LocatedIn 1; 7 Follows 10; 8 Follows 7; 9 Follows 7; 9 BelongTo 6; 8 BelongTo 5; 10 Likes 3; 7 Likes 3; 11 Follows 12; 8 Follows 11; 11 BelongTo 6; 12 Likes 4"


def toy(spark: SparkSession) -> PropertyGraph:
    attrs = [(v, i) for v, s in TOY_ITEMS.items() for i in s.split()]
    edges = [(int(a), label, int(b)) for a, label, b in (e.split() for e in TOY_EDGES.split(";"))]
    return from_rows(spark, list(TOY_ITEMS), attrs, edges)


def from_rows(spark: SparkSession, vertices, attrs, edges) -> PropertyGraph:
    make = spark.createDataFrame
    return PropertyGraph.encode(make([(v,) for v in vertices], "v long"), make(attrs, "v long, item string"), make(edges, "src long, label string, dst long"))


def build(spark: SparkSession, sf_dir: str, name: str) -> PropertyGraph:
    if name in GRAPHS:
        return from_sql(spark, sf_dir, name)
    return {"web": web, "vecnn": vecnn}[name](spark, sf_dir)


def reduce_items(g: PropertyGraph, how: str = "first") -> PropertyGraph:
    """One item for each vertex: the smallest, the most frequent or the rarest of its items (ties: smallest)."""
    if how == "first":
        attrs = g.attrs.groupBy("v").agg(F.min("item").alias("item"))
    else:
        freq = g.attrs.groupBy("item").count()  # as many rows as the vocabulary
        freq = F.broadcast(freq) if len(g.items) <= BROADCAST_NAMES else freq
        sign = -1 if how == "most" else 1
        attrs = g.attrs.join(freq, "item").groupBy("v").agg(F.min(F.struct((F.col("count") * sign).alias("c"), "item")).alias("m")).select("v", "m.item")
    return PropertyGraph(g.vertices, cut(attrs), g.edges, g.items, g.labels, g._n)


def sample_graph(g: PropertyGraph, rho: float, seed: int = 42) -> PropertyGraph:
    """A share of the vertices with the edges between them: the contrast to source sampling, which keeps the graph."""
    keep = F.pmod(F.xxhash64("v", F.lit(seed)), F.lit(1_000_000)) < int(rho * 1_000_000)
    v = cut(g.vertices.where(keep))
    edges = g.edges.join(v.select(F.col("v").alias("src")), "src", "left_semi").join(v.select(F.col("v").alias("dst")), "dst", "left_semi")
    return PropertyGraph(v, cut(g.attrs.join(v, "v", "left_semi")), cut(edges), g.items, g.labels)


def split_label_by_out_degree(g: PropertyGraph, label: str, bands=DEGREE_BANDS) -> PropertyGraph:
    """The label's edges renamed by the band of their source's out-degree under it."""
    spark = g.vertices.sparkSession
    number = g.labels.index(label)
    own = g.edges.where(F.col("label") == number)
    degree = own.groupBy("src").agg(F.count("*").alias("n"))
    name = F.lit(f"{label}_{bands[-1][1]}")
    for hi, text in reversed(bands[:-1]):
        name = F.when(F.col("n") <= hi, F.lit(f"{label}_{text}")).otherwise(name)
    names = name_table(spark, "label", g.labels)
    rest = g.edges.where(F.col("label") != number).join(names, "label").select("src", F.col("name").alias("label"), "dst")
    item_names = name_table(spark, "item", g.items)
    return PropertyGraph.encode(g.vertices, g.attrs.join(item_names, "item").select("v", F.col("name").alias("item")), own.join(degree, "src").select("src", name.alias("label"), "dst").union(rest))


def graph_stats(g: PropertyGraph) -> DataFrame:
    """One row: vertices, edges, labels, items, mean items, largest and mean in-degree."""
    spark = g.vertices.sparkSession
    degree = g.edges.groupBy("dst").count()
    e = g.edges.agg(F.count("*").alias("n_edges"), F.count_distinct("label").alias("n_labels"))
    a = g.attrs.agg(F.count("*").alias("n_attrs"), F.count_distinct("item").alias("n_items"))
    d = degree.agg(F.coalesce(F.max("count"), F.lit(0)).alias("max_in_degree"))
    # One row each: joined by a constant key.
    one = lambda df: df.withColumn("_k", F.lit(1))
    v = spark.createDataFrame([(g.n,)], "n_vertices long")
    out = one(v).join(one(e), "_k").join(one(a), "_k").join(one(d), "_k")
    return out.select("n_vertices", "n_edges", "n_labels", "n_items", F.round(F.col("n_attrs") / F.col("n_vertices"), 6).alias("mean_items"), "max_in_degree", F.round(F.col("n_edges") / F.col("n_vertices"), 6).alias("mean_in_degree"))
