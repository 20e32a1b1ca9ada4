"""Operators around the search: filters, joins, aggregates, windows, set operations, functions, subqueries, sinks."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..operators import exact, spatial
from ..sources.tables import load, views
from ..storage import new_path, stash
from ..workloads import case
from .core import DIST, PAIRS, TOP, rounded, sql_with

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


HITS = f"{sql_with()}, {TOP}, hits AS (SELECT qid, band, rank, id, dist FROM t WHERE rank <= 10)"


def micros(column: str):
    return F.unix_micros(F.col(column).cast("timestamp"))


def hits_of(spark, sf_dir):
    return case(spark, sf_dir).truth()


# --- scans and filters -------------------------------------------------------------------------------------


@query("scan_parquet", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS len FROM embeddings")
def scan_parquet(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(vectors.norm2("embedding"), 5).alias("len"))


@query("scan_roundtrip_csv_json_orc", "SELECT f.f AS format, n_nationkey, n_name, n_regionkey FROM nation, (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS f) f")
def scan_roundtrip(spark, sf_dir):
    """Nations written and read back in each format, with a stated schema."""
    rows, out = load(spark, sf_dir, "nation"), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = new_path(spark, f"nation-{fmt}")
        rows.write.format(fmt).option("header", True).save(path)
        one = spark.read.format(fmt).option("header", True).schema(rows.schema).load(path).select(F.lit(fmt).alias("format"), "n_nationkey", "n_name", "n_regionkey")
        out = one if out is None else out.unionByName(one)
    return out


@query("project_vectors", "SELECT vec_id, round(list_sum(list_transform(embedding[1:4], lambda x: CAST(x AS DOUBLE))), 6) AS head, CAST(len(embedding[33:64]) AS INTEGER) AS tail FROM embeddings")
def project_vectors(spark, sf_dir):
    e = load(spark, sf_dir, "embeddings").select("vec_id", F.struct(F.slice("embedding", 1, 4).alias("a"), F.slice("embedding", 33, 32).alias("b")).alias("v"))
    return e.select("vec_id", F.round(F.aggregate("v.a", F.lit(0.0), lambda s, x: s + x.cast("double")), 6).alias("head"), F.size("v.b").alias("tail"))


@query("filter_predicates", "SELECT doc_id, lang, n_chars FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 200 AND 5000 AND source LIKE 'src1%' AND regexp_matches(text, '[a-z]+ing') AND text IS NOT NULL")
def filter_predicates(spark, sf_dir):
    d = load(spark, sf_dir, "documents")
    return d.where(F.col("lang").isin("en", "de") & F.col("n_chars").between(200, 5000) & F.col("source").like("src1%") & F.col("text").rlike("[a-z]+ing") & F.col("text").isNotNull()).select("doc_id", "lang", "n_chars")


@query("prefilter_topk", f"{sql_with()}, h AS (SELECT qid, band, o.id, {DIST} AS dist FROM q, o, nrm WHERE o.id IN (SELECT doc_id FROM documents WHERE lang = 'en')), t AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS INTEGER) AS rank FROM h) SELECT qid, band, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10")
def prefilter_topk(spark, sf_dir):
    c = case(spark, sf_dir)
    return rounded(exact.topk(c.objects.where("attrs.lang = 'en'"), c.queries, c.norm))


@query("postfilter_topk", f"{HITS} SELECT qid, band, rank, id FROM hits JOIN documents ON doc_id = id WHERE lang = 'en'")
def postfilter_topk(spark, sf_dir):
    d = load(spark, sf_dir, "documents").where("lang = 'en'").select(F.col("doc_id").alias("id"))
    return hits_of(spark, sf_dir).join(d, "id").select("qid", "band", "rank", "id")


# --- joins -------------------------------------------------------------------------------------------------


@query("join_broadcast", f"{HITS} SELECT qid, band, rank, lang, source FROM hits JOIN documents ON doc_id = id")
def join_broadcast(spark, sf_dir):
    """The hits (k rows per query of a bounded block) are the side that is sent."""
    d = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "lang", "source")
    return d.join(F.broadcast(hits_of(spark, sf_dir)), "id").select("qid", "band", "rank", "lang", "source")


@query("join_sortmerge", "SELECT o_orderkey, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderkey")
def join_sortmerge(spark, sf_dir):
    o, li = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    return o.hint("merge").join(li, o.o_orderkey == li.l_orderkey).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("join_shuffle_hash", "SELECT c_mktsegment, count(*) AS orders, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def join_shuffle_hash(spark, sf_dir):
    o, c = load(spark, sf_dir, "orders"), load(spark, sf_dir, "customer")
    return o.join(c.hint("shuffle_hash"), o.o_custkey == c.c_custkey).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("orders"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def _outer(kind: str):
    def run(spark, sf_dir):
        e, lb = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), "label"), load(spark, sf_dir, "labels")
        return e.join(lb, "doc_id", kind).select("doc_id", "label", "quality", "toxic")

    return run


for _kind in ("left", "right", "full"):  # neither table has all ids of the other
    query(f"join_{_kind}", f"SELECT doc_id, label, quality, toxic FROM (SELECT vec_id AS doc_id, label FROM embeddings) {_kind.upper()} JOIN labels USING (doc_id)")(_outer(_kind))


@query("join_semi", "SELECT vec_id, label FROM embeddings WHERE vec_id IN (SELECT doc_id FROM labels)")
def join_semi(spark, sf_dir):
    e, lb = load(spark, sf_dir, "embeddings"), load(spark, sf_dir, "labels")
    return e.join(lb, e.vec_id == lb.doc_id, "left_semi").select("vec_id", "label")


@query("join_anti", "SELECT vec_id, label FROM embeddings WHERE vec_id NOT IN (SELECT doc_id FROM labels)")
def join_anti(spark, sf_dir):
    e, lb = load(spark, sf_dir, "embeddings"), load(spark, sf_dir, "labels")
    return e.join(lb, e.vec_id == lb.doc_id, "left_anti").select("vec_id", "label")


@query("join_theta_dominance", "SELECT a.p_partkey, count(*) AS dominated FROM part a JOIN part b ON a.p_size <= b.p_size AND a.p_retailprice <= b.p_retailprice AND (a.p_size < b.p_size OR a.p_retailprice < b.p_retailprice) GROUP BY a.p_partkey")
def join_theta_dominance(spark, sf_dir):
    """Numbers of dominated parts. Sizes are few values, so pairs of sizes are joined and prices are counted by rank, not pair by pair."""
    p = load(spark, sf_dir, "part").select("p_partkey", "p_size", "p_retailprice")
    prices = p.groupBy("p_size", "p_retailprice").agg(F.count(F.lit(1)).alias("n"))
    above = Window.partitionBy("p_size").orderBy(F.desc("p_retailprice")).rangeBetween(Window.unboundedPreceding, 0)
    curve = prices.withColumn("at_least", F.sum("n").over(above))
    sizes = p.select("p_size").distinct()
    probe = p.withColumnRenamed("p_size", "own").join(F.broadcast(sizes), F.col("p_size") >= F.col("own"))
    # for each (part, size) the number of parts of that size that are not cheaper: an as-of lookup on the price
    both = probe.select("p_size", F.col("p_retailprice").alias("price"), "p_partkey", "own", F.lit(None).cast("long").alias("at_least")).unionByName(curve.select("p_size", F.col("p_retailprice").alias("price"), F.lit(None).cast("long").alias("p_partkey"), F.lit(None).cast("int").alias("own"), "at_least"))
    asof = F.first("at_least", ignorenulls=True).over(Window.partitionBy("p_size").orderBy(F.asc("price"), F.col("p_partkey").isNull()).rowsBetween(0, Window.unboundedFollowing))
    got = both.withColumn("n", F.coalesce(asof, F.lit(0))).where("p_partkey is not null")
    twins = p.groupBy("p_size", "p_retailprice").agg(F.count(F.lit(1)).alias("same"))
    total = got.groupBy("p_partkey", F.col("own").alias("p_size"), F.col("price").alias("p_retailprice")).agg(F.sum("n").alias("n")).join(twins, ["p_size", "p_retailprice"])
    return total.select("p_partkey", (F.col("n") - F.col("same")).alias("dominated")).where("dominated > 0")


@query("join_band_distance", f"{sql_with()} SELECT a.id AS p, b.id AS x, round(0.5 * list_distance(a.e, b.e) / em + 0.5 * list_distance(a.s, b.s) / sm, 6) AS dist FROM o a JOIN o b ON a.id < b.id, nrm WHERE 0.5 * list_distance(a.e, b.e) / em + 0.5 * list_distance(a.s, b.s) / sm <= 0.6")
def join_band_distance(spark, sf_dir):
    c = case(spark, sf_dir)
    return exact.similarity_pairs(c.objects, c.norm, 0.5, 0.6).select("p", "x", F.round("dist", 6).alias("dist"))


@query("join_asof", """SELECT c.event_id, (SELECT e.event_id FROM events e WHERE e.user_id = c.user_id AND e.event_type <> 'click' AND (e.ts < c.ts OR (e.ts = c.ts AND e.event_id < c.event_id)) ORDER BY e.ts DESC, e.event_id DESC LIMIT 1) AS before FROM events c WHERE c.event_type = 'click'""")
def join_asof(spark, sf_dir):
    """The last other event of the user before each click."""
    e = load(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.withColumn("before", F.last(F.when(F.col("event_type") != "click", F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'click'").select("event_id", "before")


@query("join_interval_time", "SELECT a.event_id AS error_id, count(b.event_id) AS near FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts - INTERVAL 10 MINUTE AND b.ts <= a.ts + INTERVAL 10 MINUTE AND a.event_id <> b.event_id WHERE a.event_type = 'error' GROUP BY a.event_id")
def join_interval_time(spark, sf_dir):
    """Events of the same user within ten minutes of an error: joined on time buckets, then exactly."""
    e = load(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts", F.floor(micros("ts") / 600_000_000).alias("bucket"))
    err = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.col("ts").alias("at"), F.explode(F.array(F.col("bucket") - 1, F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    near = F.abs(micros("ts") - micros("at")) <= 600_000_000
    return err.join(e, ["user_id", "bucket"]).where(near & (F.col("event_id") != F.col("error_id"))).groupBy("error_id").agg(F.count(F.lit(1)).alias("near"))


@query("knn_join", f"{PAIRS}, r AS (SELECT p, x, CAST(row_number() OVER (PARTITION BY p ORDER BY round(0.3e0 * de + 0.7e0 * ds, 9), x) AS INTEGER) AS rank FROM pr) SELECT p, x, rank FROM r WHERE rank <= 5")
def knn_join(spark, sf_dir):
    c = case(spark, sf_dir)
    left = c.queries.where("band = 0").withColumn("alpha", F.lit(0.3))
    return exact.topk(c.objects, left, c.norm, 5).select(F.col("qid").alias("p"), F.col("id").alias("x"), "rank")


@query("knn_graph", f"{sql_with()}, d AS (SELECT a.id AS p, b.id AS x, round(0.5 * list_distance(a.e, b.e) / em + 0.5 * list_distance(a.s, b.s) / sm, 9) AS d FROM o a, o b, nrm WHERE a.id <> b.id), r AS (SELECT p, x, CAST(row_number() OVER (PARTITION BY p ORDER BY d, x) AS INTEGER) AS rank FROM d) SELECT p, x, rank FROM r WHERE rank <= 5")
def knn_graph(spark, sf_dir):
    c = case(spark, sf_dir)
    every = c.objects.select(F.col("id").alias("qid"), F.lit(0).alias("band"), F.lit(0.5).alias("alpha"), "e", "s")
    six = exact.topk(c.objects, every, c.norm, 6).where("qid <> id")
    w = Window.partitionBy("qid").orderBy("rank")
    return six.withColumn("r", F.row_number().over(w)).where("r <= 5").select(F.col("qid").alias("p"), F.col("id").alias("x"), F.col("r").alias("rank"))


# --- aggregates --------------------------------------------------------------------------------------------


@query("agg_hash", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS price, count(*) AS n FROM lineitem GROUP BY ALL")
def agg_hash(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.count(F.lit(1)).alias("n"))


@query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT date_trunc('day', ts)) AS days FROM events GROUP BY event_type")
def agg_distinct(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.date_trunc("day", "ts")).alias("days"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("users_by_sketch"))


@query("agg_percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.95), 6) AS p95, round(quantile_cont(value, 0.99), 6) AS p99 FROM events GROUP BY event_type")
def agg_percentiles(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(*[F.round(F.percentile("value", p), 6).alias(f"p{round(p * 100)}") for p in (0.5, 0.95, 0.99)])


@query("agg_kll")
def agg_kll(spark, sf_dir):
    """Quantiles of event values from a mergeable sketch."""
    e = load(spark, sf_dir, "events")
    sketch = e.groupBy("event_type").agg(F.expr("kll_sketch_agg_double(value)").alias("k"))
    return sketch.select("event_type", F.expr("kll_sketch_get_quantile_double(k, 0.5)").alias("p50"), F.expr("kll_sketch_get_quantile_double(k, 0.95)").alias("p95"))


@query("agg_vector_mean", "SELECT label, CAST(k AS INTEGER) AS place, round(avg(CAST(embedding[k] AS DOUBLE)), 6) AS mean FROM embeddings, (SELECT unnest(range(1, 65)) AS k) GROUP BY label, k")
def agg_vector_mean(spark, sf_dir):
    e = load(spark, sf_dir, "embeddings").select("label", F.posexplode("embedding").alias("place", "v"))
    return e.groupBy("label", (F.col("place") + 1).alias("place")).agg(F.round(F.avg(F.col("v").cast("double")), 6).alias("mean"))


@query("agg_max_by", "SELECT c_nationkey, max_by(c_custkey, c_acctbal) AS richest, round(max(c_acctbal), 2) AS balance FROM customer GROUP BY c_nationkey")
def agg_max_by(spark, sf_dir):
    return load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.max_by("c_custkey", "c_acctbal").alias("richest"), F.round(F.max("c_acctbal"), 2).alias("balance"))


for _name, _clause in (("agg_grouping_sets", "GROUPING SETS ((event_type, d), (event_type), ())"), ("agg_cube", "CUBE (event_type, d)"), ("agg_rollup", "ROLLUP (event_type, d)")):
    _sql = f"SELECT event_type, d, CAST(count(*) AS BIGINT) AS n, round(sum(value), 3) AS v FROM (SELECT event_type, CAST(ts AS DATE) AS d, value FROM events) GROUP BY {_clause}"

    def _grouped(spark, sf_dir, sql=_sql):
        views(spark, sf_dir)
        return spark.sql(sql)

    query(_name, _sql)(_grouped)


@query("agg_pivot", "SELECT CAST(ts AS DATE) AS d, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS \"view\" FROM events GROUP BY 1")
def agg_pivot(spark, sf_dir):
    e = load(spark, sf_dir, "events").withColumn("d", F.col("ts").cast("date"))
    return e.groupBy("d").pivot("event_type", ["click", "view"]).count().na.fill(0)


# --- windows -----------------------------------------------------------------------------------------------


@query("win_rank", "SELECT p_partkey, p_brand, CAST(row_number() OVER w1 AS INTEGER) AS rn, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size), w1 AS (PARTITION BY p_brand ORDER BY p_size, p_partkey)")
def win_rank(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return load(spark, sf_dir, "part").select("p_partkey", "p_brand", F.row_number().over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"))


@query("win_ntile_pack", "SELECT p_partkey, slab, CAST(ntile(8) OVER (PARTITION BY slab ORDER BY p_retailprice, p_partkey) AS INTEGER) AS leaf FROM (SELECT *, CAST(ntile(8) OVER (ORDER BY p_size, p_partkey) AS INTEGER) AS slab FROM part)")
def win_ntile_pack(spark, sf_dir):
    p = load(spark, sf_dir, "part").withColumn("slab", F.ntile(8).over(Window.orderBy("p_size", "p_partkey")))
    return p.select("p_partkey", "slab", F.ntile(8).over(Window.partitionBy("slab").orderBy("p_retailprice", "p_partkey")).alias("leaf"))


@query("win_running_min", "SELECT p_partkey, p_brand, min(p_retailprice) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey ROWS UNBOUNDED PRECEDING) AS low FROM part")
def win_running_min(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey").rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, sf_dir, "part").select("p_partkey", "p_brand", F.min("p_retailprice").over(w).alias("low"))


@query("win_range_frame", "SELECT event_id, count(*) OVER w AS n, round(sum(value) OVER w, 4) AS v FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS sec FROM events) WINDOW w AS (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW)")
def win_range_frame(spark, sf_dir):
    e = load(spark, sf_dir, "events").withColumn("sec", F.floor(micros("ts") / 1_000_000))
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-3600, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"), F.round(F.sum("value").over(w), 4).alias("v"))


@query("win_lag_lead", "SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER w) AS gap, lead(event_type) OVER w AS next_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_lead(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select("event_id", (micros("ts") - F.lag(micros("ts")).over(w)).alias("gap"), F.lead("event_type").over(w).alias("next_type"))


@query("win_gaps_islands", """WITH i AS (SELECT l_suppkey AS k, CAST(l_shipdate AS DATE) AS lo, CAST(l_shipdate AS DATE) + 5 AS hi, count(*) AS c FROM lineitem GROUP BY ALL),
  e AS (SELECT *, max(hi) OVER (PARTITION BY k ORDER BY lo, hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS r FROM i),
  g AS (SELECT *, sum(CASE WHEN r IS NULL OR lo > r THEN 1 ELSE 0 END) OVER (PARTITION BY k ORDER BY lo, hi ROWS UNBOUNDED PRECEDING) AS n FROM e)
  SELECT k, CAST(min(lo) AS DATE) AS lo, CAST(max(hi) AS DATE) AS hi, CAST(sum(c) AS BIGINT) AS rows FROM g GROUP BY k, n""")
def win_gaps_islands(spark, sf_dir):
    """Merged intervals of ship dates (five days each) per supplier."""
    i = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("k"), F.col("l_shipdate").cast("date").alias("lo")).groupBy("k", "lo").agg(F.count(F.lit(1)).alias("c")).withColumn("hi", F.date_add("lo", 5))
    w = Window.partitionBy("k").orderBy("lo", "hi")
    reach = F.max("hi").over(w.rowsBetween(Window.unboundedPreceding, -1))
    g = i.withColumn("r", reach).withColumn("n", F.sum(F.when(F.col("r").isNull() | (F.col("lo") > F.col("r")), 1).otherwise(0)).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return g.groupBy("k", "n").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("c").alias("rows")).drop("n")


@query("win_first_last", "SELECT DISTINCT user_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first_type"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last_type"))


# --- order, limits, sets -----------------------------------------------------------------------------------


@query("sort_global", "SELECT o_orderkey, CAST(row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) AS BIGINT) AS place FROM orders")
def sort_global(spark, sf_dir):
    """Orders with their place in a total order: a range sort, then counts of the ranges before, no single task."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").repartitionByRange(F.desc("o_totalprice"), "o_orderkey").sortWithinPartitions(F.desc("o_totalprice"), "o_orderkey")
    o = stash(o.withColumn("part", F.spark_partition_id()), "sorted")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = o.groupBy("part").agg(F.count(F.lit(1)).alias("n")).withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    own = Window.partitionBy("part").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return o.withColumn("r", F.row_number().over(own)).join(F.broadcast(offsets), "part").select("o_orderkey", (F.col("before") + F.col("r")).alias("place"))


@query("sort_within", "SELECT o_orderkey, o_custkey FROM orders")
def sort_within(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")


@query("topk_global", "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20")
def topk_global(spark, sf_dir):
    return load(spark, sf_dir, "part").select("p_partkey", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(20)


@query("topk_group", "SELECT p_brand, p_partkey, r FROM (SELECT p_brand, p_partkey, CAST(row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) AS INTEGER) AS r FROM part) WHERE r <= 3")
def topk_group(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey")
    return load(spark, sf_dir, "part").withColumn("r", F.row_number().over(w)).where("r <= 3").select("p_brand", "p_partkey", "r")


@query("limit_offset", f"{HITS} SELECT qid, band, rank, id FROM hits ORDER BY qid, band, rank LIMIT 25 OFFSET 25")
def limit_offset(spark, sf_dir):
    return hits_of(spark, sf_dir).select("qid", "band", "rank", "id").orderBy("qid", "band", "rank").offset(25).limit(25)


def _two(spark, sf_dir):
    d = load(spark, sf_dir, "documents")
    return d.where("n_chars > 800").select("lang", "source"), d.where("n_chars < 2000").select("lang", "source")


_A, _B = "SELECT lang, source FROM documents WHERE n_chars > 800", "SELECT lang, source FROM documents WHERE n_chars < 2000"
for _name, _op, _f in (
    ("set_union", "UNION", lambda a, b: a.union(b).distinct()),
    ("set_union_all", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    query(_name, f"{_A} {_op} {_B}")(lambda spark, sf_dir, f=_f: f(*_two(spark, sf_dir)))


@query("set_distinct", "SELECT count(*) AS texts FROM (SELECT DISTINCT text FROM documents)")
def set_distinct(spark, sf_dir):
    return load(spark, sf_dir, "documents").select(F.xxhash64("text").alias("h"), F.md5("text").alias("m")).distinct().agg(F.count(F.lit(1)).alias("texts"))


# --- scalar functions --------------------------------------------------------------------------------------


@query("scalar_string", "SELECT doc_id, len(list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '')) AS tokens, CAST('0x' || substr(md5(text), 1, 4) AS INTEGER) % 64 AS bucket, regexp_extract(text, '([A-Z][a-z]+)', 1) AS word, concat_ws('|', lang, upper(source), substr(text, 1, 3)) AS tag FROM documents")
def scalar_string(spark, sf_dir):
    d = load(spark, sf_dir, "documents")
    tokens = F.size(F.filter(F.split("text", "\\s+"), lambda t: t != "")).cast("long")
    return d.select("doc_id", tokens.alias("tokens"), (F.conv(F.substring(F.md5("text"), 1, 4), 16, 10).cast("int") % 64).alias("bucket"), F.regexp_extract("text", "([A-Z][a-z]+)", 1).alias("word"), F.concat_ws("|", "lang", F.upper("source"), F.substring("text", 1, 3)).alias("tag"))


@query("scalar_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(isodow(o_orderdate) AS INTEGER) AS dow, CAST(hour(o_orderdate) AS INTEGER) AS h, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(CAST(o_orderdate AS DATE) + 30 AS DATE) AS due FROM orders")
def scalar_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.date_trunc("month", d).cast("date").alias("m"), (F.weekday(d) + 1).alias("dow"), F.hour(d).alias("h"), F.datediff(d.cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.date_add(d.cast("date"), 30).alias("due"))


@query("scalar_math", "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS a, round(ln(p_size + 1), 6) AS b, round(pow(p_size, 1.5), 6) AS c, CAST(floor(p_retailprice / 7) AS BIGINT) AS d, p_partkey % 20 AS e, round(greatest(p_size, p_retailprice / 30), 6) AS f FROM part")
def scalar_math(spark, sf_dir):
    p = load(spark, sf_dir, "part")
    return p.select("p_partkey", F.round(F.sqrt("p_retailprice"), 6).alias("a"), F.round(F.log(F.col("p_size") + 1), 6).alias("b"), F.round(F.pow("p_size", F.lit(1.5)), 6).alias("c"), F.floor(F.col("p_retailprice") / 7).alias("d"), F.pmod("p_partkey", F.lit(20)).alias("e"), F.round(F.greatest(F.col("p_size").cast("double"), F.col("p_retailprice") / 30), 6).alias("f"))


@query("scalar_decimal", "SELECT l_orderkey, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2)) * (1 - CAST(l_discount AS DECIMAL(4, 2)))) AS DECIMAL(38, 4)) AS revenue FROM lineitem GROUP BY l_orderkey")
def scalar_decimal(spark, sf_dir):
    li = load(spark, sf_dir, "lineitem")
    part = F.col("l_extendedprice").cast("decimal(18,2)") * (F.lit(1).cast("decimal(4,2)") - F.col("l_discount").cast("decimal(4,2)"))
    return li.groupBy("l_orderkey").agg(F.sum(part).cast("decimal(38,4)").alias("revenue"))


@query("scalar_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0.1)) AS big, round(list_max(embedding), 6) AS top, list_position(embedding, list_max(embedding)) AS at, len(list_filter(embedding, lambda x: x < -0.3)) > 0 AS low, round(list_sum(list_transform(embedding, lambda x: abs(CAST(x AS DOUBLE)))), 5) AS l1 FROM embeddings")
def scalar_array(spark, sf_dir):
    e = F.col("embedding")
    top = F.array_max(e)
    return load(spark, sf_dir, "embeddings").select(
        "vec_id", F.size(F.filter(e, lambda x: x > 0.1)).cast("long").alias("big"), F.round(top.cast("double"), 6).alias("top"), F.array_position(e, top).cast("int").alias("at"),
        F.exists(e, lambda x: x < -0.3).alias("low"), F.round(F.aggregate(e, F.lit(0.0), lambda s, x: s + F.abs(x.cast("double"))), 5).alias("l1"),
    )


ORACLES["scalar_array"] = ORACLES["scalar_array"].replace("round(list_max(embedding), 6) AS top", "round(CAST(list_max(embedding) AS DOUBLE), 6) AS top")


@query("scalar_map_json", "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS k, count(*) FILTER (CAST(json_extract_string(props, '$.k') AS BIGINT) > 50) AS big FROM events GROUP BY event_type")
def scalar_map_json(spark, sf_dir):
    e = load(spark, sf_dir, "events").withColumn("m", F.from_json("props", "map<string,bigint>"))
    k = F.element_at("m", "k")
    return e.groupBy("event_type").agg(F.sum(k).alias("k"), F.sum(F.when(F.size(F.map_filter("m", lambda a, v: (a == "k") & (v > 50))) > 0, 1).otherwise(0)).alias("big"))


@query("scalar_case_null", "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, nullif(l.toxic, 0) AS toxic, CASE WHEN n_chars < 100 THEN 'short' WHEN n_chars < 5000 THEN 'middle' ELSE 'long' END AS size, CASE WHEN l.quality = 0 OR l.quality IS NULL THEN NULL ELSE round(n_chars / CAST(l.quality AS DOUBLE), 4) END AS per FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id")
def scalar_case_null(spark, sf_dir):
    d = load(spark, sf_dir, "documents").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    size = F.when(F.col("n_chars") < 100, "short").when(F.col("n_chars") < 5000, "middle").otherwise("long")
    return d.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), F.nullif(F.col("toxic"), F.lit(0)).alias("toxic"), size.alias("size"), F.round(F.try_divide("n_chars", F.col("quality").cast("double")), 4).alias("per"))


# --- SQL surface -------------------------------------------------------------------------------------------


def _by_sql(name: str, sql: str, oracle: str | None = None):
    def run(spark, sf_dir):
        views(spark, sf_dir)
        return spark.sql(sql)

    query(name, oracle or sql)(run)


_by_sql("subquery_corr", "SELECT o_orderkey, o_custkey FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)")
_by_sql("subquery_exists", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 150000)")
_by_sql("subquery_in", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45) AND p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_discount = 0.07)")


@query("cte_multi", f"{sql_with()}, {TOP}, le AS (SELECT qid, band, o.id, row_number() OVER (PARTITION BY qid, band ORDER BY round(list_distance(q.e, o.e) / em, 9), o.id) AS r FROM q, o, nrm), ls AS (SELECT qid, band, o.id, row_number() OVER (PARTITION BY qid, band ORDER BY round(list_distance(q.s, o.s) / sm, 9), o.id) AS r FROM q, o, nrm), un AS (SELECT qid, band, id FROM le WHERE r <= 20 UNION SELECT qid, band, id FROM ls WHERE r <= 20) SELECT qid, band, id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS r FROM h JOIN un USING (qid, band, id)) WHERE r <= 10")
def cte_multi(spark, sf_dir):
    """The merge baseline in one statement, over the registered functions: lists by blocks, once for the weights that share a query's vectors."""
    from ..functions.udx import register
    from ..operators.blocks import OBJECT_BLOCK, QUERY_BLOCK, pack_objects, pack_queries

    c = case(spark, sf_dir)
    register(spark, c)
    one = c.queries.groupBy("qid", "e", "s").agg(F.min("band").alias("band")).select("qid", "band", F.lit(0.5).alias("alpha"), "e", "s")
    stash(pack_queries(one, 256), "query-blocks").createOrReplaceTempView("query_blocks")
    pack_objects(c.objects).createOrReplaceTempView("object_blocks")
    q, o = (f"struct({', '.join(n.split()[0] for n in block.split(', '))})" for block in (QUERY_BLOCK, OBJECT_BLOCK))
    return spark.sql(f"""
      WITH q AS (SELECT *, min(band) OVER (PARTITION BY qid, e, s) AS v FROM queries),
        l AS (SELECT inline(hybrid_lists({q}, {o}, 20)) FROM query_blocks JOIN object_blocks ON true),
        r AS (SELECT qid, v, id, row_number() OVER (PARTITION BY qid, v, side ORDER BY round(d, 9), id) AS r FROM l),
        u AS (SELECT DISTINCT qid, v, id FROM r WHERE r <= 20),
        a AS (SELECT u.qid, u.v, u.id, hybrid_dist(q.e, q.s, o.e, o.s, 1D) AS de, hybrid_dist(q.e, q.s, o.e, o.s, 0D) AS ds FROM u JOIN queries q ON q.qid = u.qid AND q.band = u.v JOIN objects o ON o.id = u.id),
        d AS (SELECT q.qid, q.band, a.id, q.alpha * a.de + (1 - q.alpha) * a.ds AS dist FROM a JOIN q ON q.qid = a.qid AND q.v = a.v),
        t AS (SELECT *, row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS k FROM d)
      SELECT qid, band, id, round(dist, 6) AS dist FROM t WHERE k <= 10""")


@query("cte_recursive", f"{ORACLES['knn_graph'].replace('SELECT p, x, rank FROM r WHERE rank <= 5', '').rstrip()}, kn AS (SELECT p, x FROM r WHERE rank <= 5), st AS (SELECT min(id) AS x FROM o), go AS (SELECT x FROM st UNION SELECT kn.x FROM go JOIN kn ON kn.p = go.x) SELECT x FROM go".replace("WITH docs", "WITH RECURSIVE docs", 1))
def cte_recursive(spark, sf_dir):
    """Objects that can be reached from the least id over edges to five nearest neighbours: semi-joins to a fixpoint."""
    edges = stash(knn_graph(spark, sf_dir).select("p", "x"), "knn")
    reached = stash(case(spark, sf_dir).objects.agg(F.min("id").alias("x")), "reached")
    n = 0
    while True:
        now = reached.count()
        if now == n:
            return reached
        n = now
        reached = stash(reached.unionByName(edges.join(reached.withColumnRenamed("x", "p"), "p").select("x")).distinct(), "reached")


@query("udf_scalar", f"{sql_with()} SELECT qid, band, o.id, round({DIST}, 6) AS dist FROM q, o, nrm WHERE band = 2")
def udf_scalar(spark, sf_dir):
    from ..functions.udx import register

    c = case(spark, sf_dir)
    register(spark, c)
    return spark.sql("SELECT q.qid, q.band, o.id, round(hybrid_dist(q.e, q.s, o.e, o.s, q.alpha), 6) AS dist FROM queries q JOIN objects o ON q.band = 2")


@query("udaf_vector", "SELECT label, round(sqrt(sum(m * m)), 6) AS mean_len FROM (SELECT label, k, avg(CAST(embedding[k] AS DOUBLE)) AS m FROM embeddings, (SELECT unnest(range(1, 65)) AS k) GROUP BY label, k) GROUP BY label")
def udaf_vector(spark, sf_dir):
    from ..functions.udx import vector_mean

    m = load(spark, sf_dir, "embeddings").groupBy("label").agg(vector_mean("embedding").alias("m"))
    return m.select("label", F.round(vectors.norm2("m"), 6).alias("mean_len"))


@query("udtf_topk", f"{HITS} SELECT qid, band, CAST(rank AS INTEGER) AS rank, id FROM hits WHERE rank <= 3")
def udtf_topk(spark, sf_dir):
    """Lateral top-3 per query as a table function over a small published set of objects; larger sets are scanned."""
    from ..functions.udx import register

    c = case(spark, sf_dir)
    if not register(spark, c):
        return exact.topk(c.objects, c.queries, c.norm, 3).select("qid", "band", "rank", "id")
    return spark.sql("SELECT q.qid, q.band, t.rank, t.id FROM queries q, LATERAL hybrid_topk(q.e, q.s, q.alpha, 3) t")


@query("sample_hash", "SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 4) AS INTEGER) % 10 = 0")
def sample_hash(spark, sf_dir):
    h = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 4), 16, 10).cast("int")
    return load(spark, sf_dir, "documents").where(h % 10 == 0).select("doc_id")


@query("sink_partitioned", "SELECT source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents WHERE source = 'src1' GROUP BY source")
def sink_partitioned(spark, sf_dir):
    """Documents written by source and read with partition pruning."""
    path = new_path(spark, "by-source")
    load(spark, sf_dir, "documents").select("doc_id", "n_chars", "source").write.partitionBy("source").parquet(path)
    return spark.read.parquet(path).where("source = 'src1'").groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


@query("str_leaves")
def str_leaves(spark, sf_dir):
    c = case(spark, sf_dir, "emb_geo")
    return spatial.boxes(spatial.str_pack(c.objects), "slab", "leaf")
