"""Event graphs over the given tables, as three narrow DataFrames.

``edges(src, dst)`` is canonical: src < dst, distinct, no loops.  ``occ(node,
event)`` holds distinct occurrences; ``nodes(id)`` everything that can be a
reference, isolated event nodes included.  Each builder reads only the key and
event columns it needs.
"""

from __future__ import annotations

import gc
import tempfile
import uuid
import zipfile
from dataclasses import dataclass, field
from decimal import ROUND_HALF_UP, Decimal
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shingles import rare_run_pairs, run_pairs

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give executors this package, once an application, in case they don't have it."""
    sc = spark.sparkContext
    if sc.applicationId not in _SHIPPED:  # in local mode too: workers don't get the driver's sys.path
        root = Path(__file__).resolve().parents[1]
        at = Path(tempfile.mkdtemp(prefix="package-")) / "graph_package.zip"
        with zipfile.ZipFile(at, "w") as z:
            for f in root.rglob("*.py"):
                z.write(f, f.relative_to(root.parent))
        sc.addPyFile(str(at))
    _SHIPPED.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: spark.checkpoint.dir.  Unset, it is one of our own in local mode and an error on a cluster."""
    sc = spark.sparkContext
    ship(spark)
    if sc.getCheckpointDir() is None:
        at = spark.conf.get("spark.checkpoint.dir", None)
        if at is None and sc.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(at or tempfile.mkdtemp(prefix="vicinity-"))
    return sc.getCheckpointDir()


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of steps whose result has been written."""
    gc.collect()
    spark._jvm.System.gc()


@dataclass(frozen=True)
class EventGraph:
    nodes: DataFrame
    edges: DataFrame
    occ: DataFrame
    arcs: DataFrame | None = None  # stored adjacency, bucketed by u
    extra: DataFrame | None = None  # (id): declared nodes, beside the ends of edges and the event nodes
    kept: dict = field(default_factory=dict, compare=False)  # what is found once of nodes and edges

    @property
    def adj(self) -> DataFrame:
        """Both directions of every edge: (u, v)."""
        if self.arcs is not None:
            return self.arcs
        return self.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")).union(self.edges.select("dst", "src"))

    def event_nodes(self, a: str, b: str) -> DataFrame:
        """(node, has_a, has_b): one row for each node with either event."""
        return self.occ.where(F.col("event").isin(a, b)).groupBy("node").agg(F.max(F.col("event") == a).alias("has_a"), F.max(F.col("event") == b).alias("has_b"))

    def with_occ(self, occ: DataFrame) -> EventGraph:
        return EventGraph(self.nodes, self.edges, occ, self.arcs, kept=self.kept)

    def stored(self) -> EventGraph:
        """The graph written once in the shared folder, its adjacency bucketed and sorted by node, so that searches neither build it again nor shuffle it."""
        spark = self.nodes.sparkSession
        at, tag = shared_dir(spark), uuid.uuid4().hex
        got = {}
        for name in ("edges", "occ", "nodes"):
            df = getattr(self, name)
            if name == "nodes" and self.extra is not None:  # from what is written, not from the building join again
                own = got["edges"].select(F.col("src").alias("id")).union(got["edges"].select("dst")).union(got["occ"].select("node")).union(self.extra)
                df = own.distinct()
            df.write.parquet(f"{at}/graph_{tag}/{name}")
            got[name] = spark.read.schema(df.schema).parquet(f"{at}/graph_{tag}/{name}")
        buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
        both = EventGraph(got["nodes"], got["edges"], got["occ"]).adj
        both.repartition(buckets, "u").write.bucketBy(buckets, "u").sortBy("u").option("path", f"{at}/graph_{tag}/adj").saveAsTable(f"adj_{tag}")
        out = EventGraph(got["nodes"], got["edges"], got["occ"], spark.table(f"adj_{tag}"))
        release(spark)
        return out


def from_edges(pairs: DataFrame, occ: DataFrame, nodes: DataFrame | None = None) -> EventGraph:
    """Canonical graph from any pairs(x, y), loops and repeats included; null ends are dropped."""
    edges = pairs.toDF("x", "y").where("x <> y").select(F.least("x", "y").cast("long").alias("src"), F.greatest("x", "y").cast("long").alias("dst")).distinct()
    occ = occ.select(F.col("node").cast("long").alias("node"), "event").where("node IS NOT NULL AND event IS NOT NULL").distinct()
    own = edges.select(F.col("src").alias("id")).union(edges.select("dst")).union(occ.select("node"))
    extra = (occ.select(F.col("node").alias("id")) if nodes is None else nodes.select(F.col("id").cast("long"))).where("id IS NOT NULL")
    return EventGraph(own.union(extra).distinct(), edges, occ, None, extra)


def read(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def copurchase_part(spark: SparkSession, sf_dir: str, min_orders: int = 2) -> EventGraph:
    """Parts bought together in at least ``min_orders`` orders; events: type, brand and size of the part."""
    lines = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").where("l_orderkey IS NOT NULL AND l_partkey IS NOT NULL")
    parts = lines.groupBy("l_orderkey").agg(F.sort_array(F.collect_set("l_partkey")).alias("p")).where("size(p) > 1")
    both = parts.select("p", F.posexplode("p").alias("i", "x")).select("x", F.explode(F.expr("slice(p, i + 2, size(p))")).alias("y")).groupBy("x", "y").count().where(F.col("count") >= min_orders)
    part = read(spark, sf_dir, "part", "p_partkey", "p_type", "p_brand")
    occ = part.select(F.col("p_partkey").alias("node"), F.explode(F.array("p_type", "p_brand")).alias("event"))
    return from_edges(both.select("x", "y"), occ, part.select(F.col("p_partkey").alias("id")))


def cobuyer_customer(spark: SparkSession, sf_dir: str) -> EventGraph:
    """Customers who bought the same part from the same supplier; events: market segment."""
    lines = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    orders = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    buys = lines.join(orders, lines.l_orderkey == orders.o_orderkey).select("l_partkey", "l_suppkey", "o_custkey").distinct()
    x, y = buys.toDF("p", "s", "x"), buys.toDF("p", "s", "y")
    cust = read(spark, sf_dir, "customer", "c_custkey", "c_mktsegment")
    return from_edges(x.join(y, ["p", "s"]).where("x < y").select("x", "y"), cust.select(F.col("c_custkey").alias("node"), F.col("c_mktsegment").alias("event")), cust.select(F.col("c_custkey").alias("id")))


def order_part(spark: SparkSession, sf_dir: str) -> EventGraph:
    """Bipartite orders (even ids) and parts (odd ids); events: order status and priority, part brand."""
    lines = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    orders, part = read(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus", "o_orderpriority"), read(spark, sf_dir, "part", "p_partkey", "p_brand")
    occ = orders.select((F.col("o_orderkey") * 2).alias("node"), F.explode(F.array("o_orderstatus", "o_orderpriority")).alias("event")).union(part.select(F.col("p_partkey") * 2 + 1, "p_brand"))
    return from_edges(lines.select(F.col("l_orderkey") * 2, F.col("l_partkey") * 2 + 1), occ)


def star_tree(spark: SparkSession, sf_dir: str) -> EventGraph:
    """Region - nation - customer - order and nation - supplier; id = key * 5 + level; hubs at the top."""
    nation, customer = read(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"), read(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_mktsegment")
    orders, supplier = read(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderstatus"), read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    at = lambda c, level: (F.col(c).cast("long") * 5 + level)
    pairs = nation.select(at("n_regionkey", 0), at("n_nationkey", 1)).union(customer.select(at("c_nationkey", 1), at("c_custkey", 2))).union(orders.select(at("o_custkey", 2), at("o_orderkey", 3))).union(supplier.select(at("s_nationkey", 1), at("s_suppkey", 4)))
    occ = customer.select(at("c_custkey", 2).alias("node"), F.col("c_mktsegment").alias("event")).union(orders.select(at("o_orderkey", 3), "o_orderstatus"))
    return from_edges(pairs, occ)


def page_path(spark: SparkSession, sf_dir: str) -> EventGraph:
    """Pages (even ids by page_id) and the hrefs they hold (odd ids by hash); events: the page's language attribute."""
    pages = read(spark, sf_dir, "pages", "page_id", "html")
    links = pages.select("page_id", F.explode(F.array_distinct(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)"))).alias("href"))
    href = F.pmod(F.conv(F.substring(F.md5("href"), 1, 15), 16, 10).cast("long"), F.lit(1 << 60)) * 2 + 1
    lang = F.regexp_extract("html", '<html[^>]*lang="([^"]*)"', 1)
    return from_edges(links.select(F.col("page_id") * 2, href), pages.select((F.col("page_id") * 2).alias("node"), lang.alias("event")).where("event <> ''"))


def doc_shingle(spark: SparkSession, sf_dir: str, most: int | None = 20) -> EventGraph:
    """Documents that share a word 4-gram held by 2 to ``most`` documents, or by any number; events: language, quality and toxicity labels."""
    ship(spark)
    docs = read(spark, sf_dir, "documents", "doc_id", "text", "lang")
    labels = read(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    occ = docs.select(F.col("doc_id").alias("node"), F.col("lang").alias("event")).union(labels.select("doc_id", F.explode(F.array(F.concat(F.lit("q"), "quality"), F.concat(F.lit("t"), "toxic")))))
    texts = docs.select("doc_id", "text")
    return from_edges(run_pairs(texts, 4) if most is None else rare_run_pairs(texts, 4, most), occ, docs.select(F.col("doc_id").alias("id")))


def doc_shingle_all(spark: SparkSession, sf_dir: str) -> EventGraph:
    """Documents that share a word 4-gram, however many hold it; events as of ``doc_shingle``."""
    return doc_shingle(spark, sf_dir, None)


def user_handoff(spark: SparkSession, sf_dir: str, gap_s: int = 5, until: str = "2024-01-02") -> EventGraph:
    """Users whose events follow one another within ``gap_s`` seconds; events: event types before ``until``.

    The order in time is found within days, and across midnight by the next day's
    first event, so no task sorts the whole stream."""
    ev = read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    day = F.to_date("ts")
    near = ev.select("ts", "event_id", "user_id", day.alias("day"))
    first = near.groupBy("day").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("f")).select(F.date_sub("day", 1).alias("day"), F.col("f.ts").alias("ts"), F.col("f.event_id").alias("event_id"), F.col("f.user_id").alias("user_id"))
    w = Window.partitionBy("day").orderBy("ts", "event_id")
    both = near.union(first.select("ts", "event_id", "user_id", "day")).select("user_id", "ts", F.lead("user_id").over(w).alias("next"), F.lead("ts").over(w).alias("next_ts"))
    pairs = both.where(F.col("next_ts") <= F.col("ts") + F.expr(f"INTERVAL {gap_s} SECONDS")).select("user_id", "next")
    occ = ev.where(F.col("ts") < F.lit(until).cast("timestamp_ntz")).select(F.col("user_id").alias("node"), F.col("event_type").alias("event"))
    return from_edges(pairs, occ, ev.select(F.col("user_id").alias("id")))


_NEAR = pa.schema([("rep", pa.int64()), ("y", pa.int64()), ("c", pa.int64())])


def _in_order(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Row by row dot products, summed in the order of the components as SQL sums them."""
    out = np.zeros(len(x))
    for d in range(x.shape[1]):
        out += x[:, d] * y[:, d]
    return out


def _tenth_place(c: np.ndarray) -> np.ndarray:
    """Cosines rounded half up to ten places, as whole numbers; by decimals where a double can't tell."""
    out = np.floor(c * 1e10 + 0.5).astype(np.int64)
    for i in np.flatnonzero(np.abs(c * 1e10 - np.floor(c * 1e10) - 0.5) < 1e-3).tolist():
        out[i] = int(Decimal(repr(float(c[i]))).scaleb(10).quantize(Decimal(1), ROUND_HALF_UP))
    return out


def nearest_in_blocks(most: int, slice_rows: int = 256):
    """For a pair of blocks: (rep, y, c) of each query's ``most`` best candidates by cosine, ties to smaller ids.

    A matrix product picks all that come within 1e-9 of the last place, and these are computed anew in order."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        ask = tbl.column("asks").to_numpy().astype(bool)
        ids = tbl.column("id").to_numpy()
        vec = tbl.column("a").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(ids), -1)
        norm = np.sqrt(_in_order(vec, vec))
        q, c, out = np.flatnonzero(ask), np.flatnonzero(~ask), []
        if not len(c):
            return pa.Table.from_batches([], schema=_NEAR)
        own, m = (vec[c] / norm[c, None]).T.copy(), min(most, len(c))
        for at in range(0, len(q), slice_rows):
            mine = q[at : at + slice_rows]
            near = (vec[mine] / norm[mine, None]) @ own
            last = np.partition(near, len(c) - m, axis=1)[:, len(c) - m]
            i, j = np.nonzero(near >= last[:, None] - 1e-9)
            x, y = mine[i], c[j]
            r = np.concatenate([_tenth_place(_in_order(vec[x[k : k + 65536]], vec[y[k : k + 65536]]) / (norm[x[k : k + 65536]] * norm[y[k : k + 65536]])) for k in range(0, len(x), 65536)])
            order = np.lexsort((ids[y], -r, i))
            i, y, r = i[order], y[order], r[order]
            head = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
            keep = np.arange(len(i)) - np.repeat(head, np.diff(np.r_[head, len(i)])) < most
            out.append(pa.RecordBatch.from_arrays([pa.array(ids[mine[i[keep]]]), pa.array(ids[y[keep]]), pa.array(r[keep])], schema=_NEAR))
        return pa.Table.from_batches(out, schema=_NEAR)

    return run


def embed_knn(spark: SparkSession, sf_dir: str, k: int = 5, block: int = 8192) -> EventGraph:
    """Each vector with its ``k`` nearest by cosine in doubles; events: label.

    Exact: all pairs of blocks of distinct vectors are compared by matrix products.  Equal vectors are
    one query, and of their ids the ``k`` + 1 smallest are candidates, as no list holds more of them.
    Vectors that are null or zero or hold null or non-finite components take no part."""
    ship(spark)
    given = read(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    fit = "embedding IS NOT NULL AND forall(embedding, e -> e IS NOT NULL AND NOT isnan(e) AND abs(e) <> double('infinity')) AND exists(embedding, e -> e <> 0)"
    same = Window.partitionBy("a")
    v = given.where(fit).where("vec_id IS NOT NULL").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("a")).distinct()
    v = v.select("id", "a", F.min("id").over(same).alias("rep"), F.row_number().over(same.orderBy("id")).alias("r"))
    some = v.where(F.col("r") <= k + 1).withColumn("dim", F.size("a"))
    at = read(spark, sf_dir, "embeddings", "vec_id").count() // block + 1
    mine = F.pmod(F.xxhash64("id"), F.lit(at)).cast("int")
    others = F.explode(F.sequence(F.lit(0), F.lit(at - 1)))
    asks = some.where("r = 1").select("dim", mine.alias("qb"), others.alias("cb"), "id", "a", F.lit(1).alias("asks"))
    held = some.select("dim", others.alias("qb"), mine.alias("cb"), "id", "a", F.lit(0).alias("asks"))
    near = asks.unionByName(held).groupBy("dim", "qb", "cb").applyInArrow(nearest_in_blocks(k + 1), "rep long, y long, c long")
    best = near.withColumn("p", F.row_number().over(Window.partitionBy("rep").orderBy(F.desc("c"), "y"))).where(F.col("p") <= k + 1)
    pairs = v.select(F.col("id").alias("x"), "rep").join(best, "rep").where("x <> y").withColumn("p", F.row_number().over(Window.partitionBy("x").orderBy("p")))
    return from_edges(pairs.where(F.col("p") <= k).select("x", "y"), given.select(F.col("vec_id").alias("node"), F.col("label").cast("string").alias("event")))


_STORED: dict[tuple, EventGraph] = {}


def _state(spark: SparkSession, sf_dir: str) -> tuple:
    """Names, sizes and times of a folder's files, to tell whether its tables have changed."""
    at = spark._jvm.org.apache.hadoop.fs.Path(sf_dir)
    files = at.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(at)
    return tuple(sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in files))


def stored_graph(spark: SparkSession, sf_dir: str, name: str) -> EventGraph:
    """The named graph, built and stored once an application for as long as the tables stay as they are."""
    key = (spark.sparkContext.applicationId, sf_dir, name, _state(spark, sf_dir))
    if key not in _STORED:
        _STORED[key] = BUILDERS[name](spark, sf_dir).stored()
    return _STORED[key]


BUILDERS = {f.__name__: f for f in (copurchase_part, cobuyer_customer, order_part, star_tree, page_path, doc_shingle, user_handoff, embed_knn)}
