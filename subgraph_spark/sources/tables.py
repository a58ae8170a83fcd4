"""Target graphs built from the given tables, and the same graphs as SQL for the oracles."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import TargetGraph
from ..session import materialise

KIND = {"region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6}
KIND_STEP = 10**12


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def range_join(left: DataFrame, right: DataFrame, keys: list[str], at: str, other_at: str, days: int) -> DataFrame:
    """Rows with equal keys and ``other_at`` 0 to ``days`` days after ``at``: an equi-join on key and day, one day at a time.

    Adds ``lag``. Days are whole (``at`` and ``other_at`` are dates).
    """
    shifted = left.withColumn("lag", F.explode(F.sequence(F.lit(0), F.lit(days)))).withColumn("on_day", F.date_add(F.col(at), F.col("lag")))
    return shifted.join(right.withColumnRenamed(other_at, "on_day"), [*keys, "on_day"])


def supplier_echo(spark: SparkSession, sf_dir: str, days: int = 1) -> TargetGraph:
    """Supplier to supplier whose line of the same part ships 0 or 1 days later; labelled with the days between."""
    line = read(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", F.to_date("l_shipdate").alias("day")).distinct()
    later = line.select("l_partkey", F.col("l_suppkey").alias("dst"), F.col("day").alias("other"))
    edges = range_join(line.withColumnRenamed("l_suppkey", "src"), later, ["l_partkey"], "day", "other", days).filter("src <> dst")
    vertices = read(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("vid"), F.col("s_nationkey").cast("string").alias("vlabel"))
    return TargetGraph.of(vertices, edges.select("src", "dst", F.col("lag").cast("string").alias("elabel")), name="supplier_echo")


def part_flow(spark: SparkSession, sf_dir: str) -> TargetGraph:
    """Part to the part on the next line of an order."""
    line = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_linenumber")
    after = line.select("l_orderkey", F.col("l_partkey").alias("dst"), (F.col("l_linenumber") - 1).alias("l_linenumber"))
    edges = line.withColumnRenamed("l_partkey", "src").join(after, ["l_orderkey", "l_linenumber"]).filter("src <> dst")
    vertices = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("vid"), F.col("p_brand").alias("vlabel"))
    return TargetGraph.of(vertices, edges.select("src", "dst", F.lit(None).cast("string").alias("elabel")), name="part_flow")


def next_within(events: DataFrame, order: list[str], at: str, seconds: int, carried: list[str]) -> DataFrame:
    """As-of join with the event that comes next overall, if it comes within ``seconds``; adds ``next_`` columns.

    Time is cut into stretches of that length, in which the next event lies in the same or the following one: no window over all
    rows is needed, only the first event of each stretch is handed to the one before.
    """
    rows = events.withColumn("cut", F.floor(F.unix_micros(F.col(at).cast("timestamp")) / (seconds * 1_000_000)))
    run = Window.partitionBy("cut").orderBy(*order)
    following = F.struct(*[F.col(c) for c in dict.fromkeys([*order, *carried])])
    rows = rows.withColumn("inner", F.lead(following).over(run))
    first = rows.groupBy(F.expr("cut - 1").alias("cut")).agg(F.min(following).alias("outer"))
    rows = rows.join(first, "cut", "left").withColumn("next", F.coalesce("inner", "outer"))
    gap = F.unix_micros(F.col(f"next.{at}").cast("timestamp")) - F.unix_micros(F.col(at).cast("timestamp"))
    kept = [F.col(f"next.{c}").alias(f"next_{c}") for c in dict.fromkeys([*order, *carried])]
    return rows.filter(gap <= seconds * 1_000_000).select(*events.columns, *kept)


def relay_edges(events: DataFrame, minutes: int = 10) -> DataFrame:
    near = next_within(events.select("event_id", "ts", "user_id", "event_type"), ["ts", "event_id"], "ts", 60 * minutes, ["user_id", "event_type"])
    return near.select(F.col("user_id").alias("src"), F.col("next_user_id").alias("dst"), F.col("next_event_type").alias("elabel")).filter("src <> dst")


def user_relay(spark: SparkSession, sf_dir: str, simple: bool = True) -> TargetGraph:
    """User to the user of the next event overall, within ten minutes; labelled with that event's type."""
    events = read(spark, sf_dir, "events")
    kinds = events.groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    top = kinds.groupBy("user_id").agg(F.min(F.struct((-F.col("n")).alias("n"), "event_type")).alias("top"))
    return TargetGraph.of(top.select(F.col("user_id").alias("vid"), F.col("top.event_type").alias("vlabel")), relay_edges(events), simple, "user_relay")


def commerce(spark: SparkSession, sf_dir: str) -> TargetGraph:
    """Regions, nations, customers, suppliers, parts and orders with their relations."""
    t = lambda name: read(spark, sf_dir, name)
    of = lambda kind, column: (F.lit(KIND[kind] * KIND_STEP) + F.col(column)).cast("long")
    keys = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "order": "o_orderkey"}
    vertices = None
    for kind, key in keys.items():
        rows = t("orders" if kind == "order" else kind).select(of(kind, key).alias("vid"), F.lit(kind).alias("vlabel"))
        vertices = rows if vertices is None else vertices.unionByName(rows)
    edges = None
    line = t("lineitem")
    for rows, a, x, b, y, label in (
        (t("nation"), "nation", "n_nationkey", "region", "n_regionkey", "in_region"),
        (t("customer"), "customer", "c_custkey", "nation", "c_nationkey", "in_nation"),
        (t("supplier"), "supplier", "s_suppkey", "nation", "s_nationkey", "in_nation"),
        (t("orders"), "order", "o_orderkey", "customer", "o_custkey", "placed_by"),
        (line, "order", "l_orderkey", "part", "l_partkey", "contains"),
        (line, "order", "l_orderkey", "supplier", "l_suppkey", "ships_from"),
    ):
        one = rows.select(of(a, x).alias("src"), of(b, y).alias("dst"), F.lit(label).alias("elabel"))
        edges = one if edges is None else edges.unionByName(one)
    return TargetGraph.of(vertices, edges, name="commerce")


def turn_chain(spark: SparkSession, sf_dir: str) -> TargetGraph:
    """Turn to the next turn of a conversation; labelled with the role."""
    turns = read(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("vid"), F.col("role").alias("vlabel"))
    after = turns.select(F.col("vid").alias("dst"))
    edges = turns.select(F.col("vid").alias("src"), (F.col("vid") + 1).alias("dst")).join(after, "dst", "left_semi")
    return TargetGraph.of(turns, edges.select("src", "dst", F.lit(None).cast("string").alias("elabel")), name="turn_chain")


def nearest(vectors: DataFrame, k: int, block: int = 1024) -> DataFrame:
    """(src, dst, rank): the k largest inner products in double precision, ties to the smaller id.

    Exact, so all blocks meet all blocks; a task holds two, and hands on k rows per vector.
    """
    packed = vectors.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    n = max(1, -(-vectors.count() // block))
    blocks = packed.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(n))).groupBy("part").agg(F.collect_list(F.struct("id", "v")).alias("rows"))
    blocks = materialise(blocks, "blocks")
    both = blocks.select(F.col("rows").alias("a")).crossJoin(blocks.select(F.col("rows").alias("b"))).repartition(min(n * n, 4096))

    def top(batches):
        for batch in batches:
            for a, b in zip(batch.column(0), batch.column(1), strict=True):
                sides = []
                for x in (a, b):
                    ids = x.values.field("id").to_numpy()
                    sides.append((ids, x.values.field("v").flatten().to_numpy().reshape(len(ids), -1)))
                (ai, av), (bi, bv) = sides
                order = np.argsort(bi)
                bi, bv = bi[order], bv[order]
                score = av @ bv.T
                score[ai[:, None] == bi[None, :]] = -np.inf
                best = np.argsort(-score, axis=1, kind="stable")[:, :k]
                yield pa.RecordBatch.from_pydict({"src": np.repeat(ai, best.shape[1]), "dst": bi[best].ravel(), "score": np.take_along_axis(score, best, 1).ravel()})

    found = both.mapInArrow(top, "src long, dst long, score double").filter("score > double('-infinity')")
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("score"), "dst"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("src", "dst", "rank")


def embed_knn(spark: SparkSession, sf_dir: str, k: int = 5) -> TargetGraph:
    vectors = read(spark, sf_dir, "embeddings")
    return TargetGraph.of(vectors.select(F.col("vec_id").alias("vid"), F.col("label").cast("string").alias("vlabel")), nearest(vectors, k).select("src", "dst", F.lit(None).cast("string").alias("elabel")), name="embed_knn")


def page_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, path), once each."""
    pages = read(spark, sf_dir, "pages")
    return pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))).alias("path")).distinct()


def path_vid(column: str = "path"):
    """Paths have negative ids, from their hash; pages keep theirs."""
    return -1 - F.shiftrightunsigned(F.xxhash64(column), 1)


def page_links(spark: SparkSession, sf_dir: str) -> TargetGraph:
    """Page to each path that it links. A page's label is its host's last part, a path's is ``path``."""
    links = page_paths(spark, sf_dir)
    host = F.regexp_extract(F.coalesce("url", F.lit("")), r"^[a-z]+://[^/?#]*\.([A-Za-z]+)", 1)
    pages = read(spark, sf_dir, "pages").select(F.col("page_id").alias("vid"), host.alias("vlabel")).join(links.select(F.col("page_id").alias("vid")).distinct(), "vid", "left_semi")
    paths = links.select(path_vid().alias("vid"), F.lit("path").alias("vlabel")).distinct()
    return TargetGraph.of(pages.unionByName(paths), links.select(F.col("page_id").alias("src"), path_vid().alias("dst"), F.lit(None).cast("string").alias("elabel")), name="page_links")


def shared_lines(spark: SparkSession, sf_dir: str, least: int = 20, most: int = 50) -> DataFrame:
    """(src, dst), src < dst: documents that share a trimmed line of ``least`` characters which at most ``most`` documents have."""
    docs = read(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.md5(F.trim("line")).alias("line"), F.length(F.trim("line")).alias("n")).filter(F.col("n") >= least).select("doc_id", "line").distinct()
    some = docs.groupBy("line").agg(F.count("*").alias("n")).filter(F.col("n").between(2, most)).select("line")
    docs = docs.join(some, "line")
    return docs.withColumnRenamed("doc_id", "src").join(docs.withColumnRenamed("doc_id", "dst"), "line").filter("src < dst").select("src", "dst").distinct()


def doc_share(spark: SparkSession, sf_dir: str) -> TargetGraph:
    """Documents that share a line; labelled with the language."""
    vertices = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), F.col("lang").alias("vlabel"))
    return TargetGraph.of(vertices, shared_lines(spark, sf_dir).withColumn("elabel", F.lit(None).cast("string")), name="doc_share")


def line_share(spark: SparkSession, sf_dir: str, least: int = 20) -> TargetGraph:
    """Every line of ``least`` characters, however many documents have it: its smallest document leads to the others.

    The components are those of all pairs, from edges whose number is that of the lines' occurrences.
    """
    lines = read(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).select("doc_id", F.trim("line").alias("line")).filter(F.length("line") >= least)
    lines = lines.select("doc_id", F.md5("line").alias("line")).distinct()
    first = lines.groupBy("line").agg(F.min("doc_id").alias("src"), F.count("*").alias("n")).filter("n > 1")
    edges = lines.join(first, "line").filter("doc_id <> src").select("src", F.col("doc_id").alias("dst"), F.lit(None).cast("string").alias("elabel"))
    vertices = read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vid"), F.col("lang").alias("vlabel"))
    return TargetGraph.of(vertices, edges, name="line_share")


#: Added to a benchmark item's id, to tell it from a document's.
ITEM = 10**12


def doc_benchmark(spark: SparkSession, sf_dir: str, most_items: int = 100_000) -> TargetGraph:
    """A document to each benchmark item whose text it contains. The items are a given set: their number is checked, and they meet all documents."""
    items = read(spark, sf_dir, "benchmark").select((F.col("item_id") + ITEM).alias("dst"), F.col("text").alias("item"))
    n = items.count()
    if n > most_items:
        raise ValueError(f"{n} benchmark items; {most_items} are allowed")
    docs = read(spark, sf_dir, "documents")
    edges = docs.join(F.broadcast(items), F.contains("text", "item")).select(F.col("doc_id").alias("src"), "dst", F.lit(None).cast("string").alias("elabel"))
    vertices = docs.select(F.col("doc_id").alias("vid"), F.col("lang").alias("vlabel")).unionByName(items.select(F.col("dst").alias("vid"), F.lit("benchmark").alias("vlabel")))
    return TargetGraph.of(vertices, edges, name="doc_benchmark")


def uniform_dense(spark: SparkSession, sf_dir: str, n: int = 100, share: int = 1500, labels: int = 31, seed: int = 1) -> TargetGraph:
    """A seeded target of ``n`` vertices with evenly spread labels; about ``share`` of 10,007 pairs are edges. It reads no table."""
    vertices = spark.range(n).select(F.col("id").alias("vid"), F.concat(F.lit("L"), (F.col("id") * F.col("id") * 13 + F.col("id") * 7 + seed) % labels).alias("vlabel"))
    pairs = spark.range(n * n).select(F.expr(f"id div {n}").alias("src"), (F.col("id") % n).alias("dst"))
    kept = pairs.filter((F.col("src") * 7919 + F.col("dst") * 104729 + F.col("src") * F.col("dst") * 31 + seed * 1299709) % 10007 < share)
    return TargetGraph.of(vertices, kept.filter("src <> dst").select("src", "dst", F.lit(None).cast("string").alias("elabel")), name="uniform_dense")


def bucket_flow(spark: SparkSession, sf_dir: str, n: int = 100, most: int = 15, labels: int = 31) -> TargetGraph:
    """``n`` buckets of keys with evenly spread labels; each leads to the ``most`` buckets of parts that its orders have most lines of, ties to the smaller."""
    line = read(spark, sf_dir, "lineitem").select((F.col("l_orderkey") % n).alias("src"), (F.col("l_partkey") % n).alias("dst")).filter("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("n"))
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("n"), "dst"))
    edges = line.withColumn("rank", rank).filter(F.col("rank") <= most).select("src", "dst", F.lit(None).cast("string").alias("elabel"))
    v = F.col("vid")
    vertices = read(spark, sf_dir, "part").select((F.col("p_partkey") % n).alias("vid")).distinct().select("vid", F.concat(F.lit("L"), (v * v * 13 + v * 7 + 1) % labels).alias("vlabel"))
    return TargetGraph.of(vertices, edges, name="bucket_flow")


BUILDERS = {f.__name__: f for f in (supplier_echo, part_flow, user_relay, commerce, turn_chain, embed_knn, page_links, doc_share, line_share, doc_benchmark, uniform_dense, bucket_flow)}

#: The vertex and edge tables of each builder, as the oracle's SQL.
_EDGE_SQL = {
    "bucket_flow": "SELECT src, dst, CAST(NULL AS VARCHAR) AS elabel FROM (SELECT l_orderkey % 100 AS src, l_partkey % 100 AS dst, row_number() OVER (PARTITION BY l_orderkey % 100 ORDER BY count(*) DESC, l_partkey % 100) AS r FROM lineitem WHERE l_orderkey % 100 <> l_partkey % 100 GROUP BY 1, 2) q WHERE r <= 15",
    "uniform_dense": "SELECT a.i AS src, b.i AS dst, CAST(NULL AS VARCHAR) AS elabel FROM range(100) a(i), range(100) b(i) WHERE a.i <> b.i AND (a.i * 7919 + b.i * 104729 + a.i * b.i * 31 + 1299709) % 10007 < 1500",
    "supplier_echo": "SELECT x.l_suppkey AS src, y.l_suppkey AS dst, CAST(min(date_diff('day', x.l_shipdate, y.l_shipdate)) AS VARCHAR) AS elabel FROM lineitem x JOIN lineitem y ON x.l_partkey = y.l_partkey AND x.l_suppkey <> y.l_suppkey AND y.l_shipdate >= x.l_shipdate AND y.l_shipdate <= x.l_shipdate + INTERVAL 1 DAY GROUP BY 1, 2",
    "part_flow": "SELECT DISTINCT x.l_partkey AS src, y.l_partkey AS dst, CAST(NULL AS VARCHAR) AS elabel FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND y.l_linenumber = x.l_linenumber + 1 WHERE x.l_partkey <> y.l_partkey",
    "user_relay": "SELECT user_id AS src, nu AS dst, min(nt) AS elabel FROM (SELECT user_id, ts, lead(user_id) OVER w AS nu, lead(event_type) OVER w AS nt, lead(ts) OVER w AS nts FROM events WINDOW w AS (ORDER BY ts, event_id)) q WHERE nts <= ts + INTERVAL 10 MINUTE AND user_id <> nu GROUP BY 1, 2",
    "turn_chain": "SELECT a.conv_id * 1000 + a.turn AS src, b.conv_id * 1000 + b.turn AS dst, CAST(NULL AS VARCHAR) AS elabel FROM conversations a JOIN conversations b ON b.conv_id = a.conv_id AND b.turn = a.turn + 1",
    "commerce": " UNION ".join(f"SELECT CAST({KIND[a] * KIND_STEP} AS BIGINT) + {x} AS src, CAST({KIND[b] * KIND_STEP} AS BIGINT) + {y} AS dst, '{e}' AS elabel FROM {t}" for t, a, x, b, y, e in (("nation", "nation", "n_nationkey", "region", "n_regionkey", "in_region"), ("customer", "customer", "c_custkey", "nation", "c_nationkey", "in_nation"), ("supplier", "supplier", "s_suppkey", "nation", "s_nationkey", "in_nation"), ("orders", "order", "o_orderkey", "customer", "o_custkey", "placed_by"), ("lineitem", "order", "l_orderkey", "part", "l_partkey", "contains"), ("lineitem", "order", "l_orderkey", "supplier", "l_suppkey", "ships_from"))),
    "line_share": "SELECT DISTINCT min(doc_id) OVER (PARTITION BY line) AS src, doc_id AS dst, CAST(NULL AS VARCHAR) AS elabel FROM li QUALIFY min(doc_id) OVER (PARTITION BY line) <> doc_id",
    "doc_benchmark": "SELECT d.doc_id AS src, 1000000000000 + b.item_id AS dst, CAST(NULL AS VARCHAR) AS elabel FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "doc_share": "SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst, CAST(NULL AS VARCHAR) AS elabel FROM li a JOIN li b ON a.line = b.line AND a.doc_id < b.doc_id WHERE a.line IN (SELECT line FROM li GROUP BY line HAVING count(*) BETWEEN 2 AND 50)",
    "embed_knn": "SELECT src, dst, CAST(NULL AS VARCHAR) AS elabel FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_inner_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) q WHERE r <= 5",
}
_VERTEX_SQL = {
    "bucket_flow": "SELECT DISTINCT p_partkey % 100 AS vid, 'L' || ((p_partkey % 100) * (p_partkey % 100) * 13 + (p_partkey % 100) * 7 + 1) % 31 AS vlabel FROM part",
    "uniform_dense": "SELECT i AS vid, 'L' || ((i * i * 13 + i * 7 + 1) % 31) AS vlabel FROM range(100) t(i)",
    "supplier_echo": "SELECT s_suppkey AS vid, CAST(s_nationkey AS VARCHAR) AS vlabel FROM supplier",
    "part_flow": "SELECT p_partkey AS vid, p_brand AS vlabel FROM part",
    "user_relay": "SELECT user_id AS vid, event_type AS vlabel FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS r FROM events GROUP BY 1, 2) q WHERE r = 1",
    "turn_chain": "SELECT conv_id * 1000 + turn AS vid, role AS vlabel FROM conversations",
    "commerce": " UNION ALL ".join(f"SELECT CAST({KIND[k] * KIND_STEP} AS BIGINT) + {c} AS vid, '{k}' AS vlabel FROM {t}" for k, t, c in (("region", "region", "r_regionkey"), ("nation", "nation", "n_nationkey"), ("customer", "customer", "c_custkey"), ("supplier", "supplier", "s_suppkey"), ("part", "part", "p_partkey"), ("order", "orders", "o_orderkey"))),
    "doc_share": "SELECT doc_id AS vid, lang AS vlabel FROM documents",
    "line_share": "SELECT doc_id AS vid, lang AS vlabel FROM documents",
    "doc_benchmark": "SELECT doc_id AS vid, lang AS vlabel FROM documents UNION ALL SELECT 1000000000000 + item_id, 'benchmark' FROM benchmark",
    "embed_knn": "SELECT vec_id AS vid, CAST(label AS VARCHAR) AS vlabel FROM embeddings",
}
_LINES = r"li AS MATERIALIZED (SELECT DISTINCT doc_id, trim(l, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents) q WHERE length(trim(l, ' ')) >= 20), "
_BEFORE = {"doc_share": _LINES, "line_share": _LINES}


def graph_sql(name: str) -> str:
    """``WITH v AS (...), e AS (...)`` for a builder; write the rest behind it."""
    return f"WITH {_BEFORE.get(name, '')}v AS MATERIALIZED ({_VERTEX_SQL[name]}), e AS MATERIALIZED ({_EDGE_SQL[name]})"
