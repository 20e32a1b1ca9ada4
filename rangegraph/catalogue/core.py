"""Queries of the methods, variants, baselines, measures and experiments, with SQL where SQL can express them."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..baselines import graphs
from ..functions import alpha as al
from ..functions import vectors
from ..operators import bsp, exact, index, metrics, normalisers, pareto, prune, seeds, spatial, whole
from ..schema import BuildParams, SearchParams, ShardParams
from ..sources import tables
from ..storage import stash
from ..workloads import Case, asked, case, gated, merged, plain, runs_of, together

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# --- SQL of the workloads ----------------------------------------------------------------------------------


def _vector_sql(width: int, place: str = "true", of: str = "documents") -> str:
    return f"""
      tok{width} AS (
        SELECT doc_id, t, i FROM (
          SELECT doc_id, unnest(p) AS t, generate_subscripts(p, 1) AS i
          FROM (SELECT doc_id, list_filter(regexp_split_to_array(text, '\\s+'), lambda x: x <> '') AS p FROM {of})) WHERE {place}),
      cnt{width} AS (SELECT doc_id, CAST('0x' || substr(md5(t), 1, 4) AS INTEGER) % {width} AS k, count(*) AS n FROM tok{width} GROUP BY ALL),
      len{width} AS (SELECT doc_id, sqrt(sum(n * n)) AS l FROM cnt{width} GROUP BY doc_id),
      vec{width} AS (
        SELECT d.doc_id, list(CAST(CAST(coalesce(c.n / l.l, 0) AS FLOAT) AS DOUBLE) ORDER BY r.k) AS v
        FROM {of} d CROSS JOIN (SELECT unnest(range({width})) AS k) r LEFT JOIN cnt{width} c ON c.doc_id = d.doc_id AND c.k = r.k
        LEFT JOIN len{width} l ON l.doc_id = d.doc_id GROUP BY d.doc_id)"""


_D = "lambda x: CAST(x AS DOUBLE)"
_COORD = "[CAST(CAST(n % 5 + ((i * 7919) % 1000) / 2500e0 AS FLOAT) AS DOUBLE), CAST(CAST(n // 5 + ((i * 104729) % 1000) / 2500e0 AS FLOAT) AS DOUBLE)]"
SQL_ROWS = {
    "emb_split": f"w AS (SELECT vec_id AS id, list_transform(embedding[1:32], {_D}) AS e, list_transform(embedding[33:64], {_D}) AS s FROM embeddings)",
    "emb_geo": f"w AS (SELECT i AS id, list_transform(embedding, {_D}) AS e, {_COORD} AS s FROM (SELECT vec_id AS i, c_nationkey AS n, embedding FROM embeddings JOIN customer ON vec_id = c_custkey))",
    "text_emb": "docs AS (SELECT doc_id, text FROM documents WHERE doc_id IN (SELECT vec_id FROM embeddings))," + _vector_sql(64, of="docs") + f", w AS (SELECT doc_id AS id, v AS e, list_transform(embedding, {_D}) AS s FROM vec64 JOIN embeddings ON vec_id = doc_id)",
    "doc_pair": _vector_sql(64, "i % 2 = 1") + "," + _vector_sql(32, "i % 2 = 0") + ", w AS (SELECT a.doc_id AS id, a.v AS e, b.v AS s FROM vec64 a JOIN vec32 b USING (doc_id))",
    "doc_geo": "docs AS (SELECT doc_id, text FROM documents WHERE doc_id IN (SELECT c_custkey FROM customer))," + _vector_sql(64, of="docs") + f", w AS (SELECT i AS id, v AS e, {_COORD} AS s FROM (SELECT doc_id AS i, c_nationkey AS n, v FROM vec64 JOIN customer ON doc_id = c_custkey))",
    "line_geo": """st AS (SELECT avg(l_quantity) AS m1, stddev_pop(l_quantity) AS d1, avg(l_extendedprice) AS m2, stddev_pop(l_extendedprice) AS d2, avg(l_discount) AS m3, stddev_pop(l_discount) AS d3, avg(l_tax) AS m4, stddev_pop(l_tax) AS d4 FROM lineitem),
      w AS (SELECT (l_orderkey * 8 + l_linenumber) * 64 + copy AS id,
        list_transform([(l_quantity - m1) / d1, (l_extendedprice - m2) / d2, (l_discount - m3) / d3, (l_tax - m4) / d4,
          CAST(l_returnflag = 'A' AS DOUBLE), CAST(l_returnflag = 'N' AS DOUBLE), CAST(l_returnflag = 'R' AS DOUBLE), CAST(l_linestatus = 'O' AS DOUBLE), CAST(l_linestatus = 'F' AS DOUBLE)], lambda x: CAST(CAST(x AS FLOAT) AS DOUBLE)) AS e,
        [CAST(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE), CAST(p_size AS DOUBLE)] AS s
        FROM (SELECT *, row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS copy FROM lineitem)
        JOIN part ON l_partkey = p_partkey, st)""",
    "event_stream": """w AS (SELECT event_id AS id,
        list_transform([CAST(event_type = 'click' AS INT), CAST(event_type = 'error' AS INT), CAST(event_type = 'purchase' AS INT), CAST(event_type = 'signup' AS INT), CAST(event_type = 'view' AS INT),
          ln(1 + value), CAST(json_extract_string(props, '$.k') AS DOUBLE) / 100, (user_id % 10) / 10e0], lambda x: CAST(CAST(x AS FLOAT) AS DOUBLE)) AS e,
        [CAST(hour(ts) AS DOUBLE), CAST(day(ts) AS DOUBLE)] AS s FROM events)""",
}


def sql_with(name: str = "text_emb", norm: bool = True) -> str:
    """WITH clause: w (all rows), o (objects), q (queries), nrm (normalisers)."""
    base = f"""WITH {SQL_ROWS[name]},
      o AS (SELECT * FROM w WHERE id % 20 <> 7),
      q AS (SELECT id AS qid, CAST(b.band AS INTEGER) AS band, 0.2e0 * b.band + 0.2e0 * ((id * 7919 + b.band * 104729) % 1000) / 1e3 AS alpha, e, s FROM w CROSS JOIN (SELECT unnest(range(5)) AS band) b WHERE id % 20 = 7)"""
    return base + (", nrm AS (SELECT max(list_distance(a.e, b.e)) AS em, max(list_distance(a.s, b.s)) AS sm FROM o a JOIN o b ON a.id <= b.id)" if norm else "")


DIST = "q.alpha * list_distance(q.e, o.e) / em + (1 - q.alpha) * list_distance(q.s, o.s) / sm"
TOP = f"""h AS (SELECT qid, band, o.id, {DIST} AS dist FROM q, o, nrm),
      t AS (SELECT qid, band, CAST(row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS INTEGER) AS rank, id, dist FROM h)"""
TOP10 = f"{sql_with()}, {TOP} SELECT qid, band, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10"
PAIRS = f"""{sql_with()}, pr AS (SELECT qid AS p, o.id AS x, round(list_distance(q.e, o.e) / em, 12) AS de, round(list_distance(q.s, o.s) / sm, 12) AS ds FROM q, o, nrm WHERE band = 0)"""


def rounded(hits: DataFrame) -> DataFrame:
    return hits.select("qid", "band", "rank", "id", F.round("dist", 6).alias("dist"))


def pairs_of(c: Case) -> DataFrame:
    """p (a query's row), x, de, ds."""
    nodes = c.queries.where("band = 0").select(F.col("qid").alias("id"), "e", "s")
    measured = lambda: exact.pair_distances(c.objects, c.norm, nodes).select("p", "x", F.round("de", 12).alias("de"), F.round("ds", 12).alias("ds"))
    return c.once("pairs", lambda: stash(measured(), "pairs"))


def pool_of(c: Case, most: int) -> DataFrame:
    """The rows of pairs_of that may be in the first `most` layers of their pool, and some more."""

    def measured() -> DataFrame:
        if not whole.fits(c.objects):
            return pairs_of(c)
        return stash(whole.pool(c.objects, c.norm, c.queries.where("band = 0").select(F.col("qid").alias("id"), "e", "s"), most), "pool")

    return c.once(("pool", most), measured)


# --- workload views ----------------------------------------------------------------------------------------


def _view(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = tables.WORKLOADS[name](spark, sf_dir)
        return rows.select("id", F.round(vectors.norm2("e"), 5).alias("e_len"), F.round(vectors.norm2("s"), 5).alias("s_len"), F.size("e").cast("long").alias("e_dim"), F.size("s").cast("long").alias("s_dim"))

    return run


for _name in tables.WORKLOADS:
    _sql = SQL_ROWS.get(_name)
    _len = lambda c: f"round(sqrt(list_sum(list_transform({c}, lambda x: x * x))), 5)"
    query(f"wl_{_name}", _sql and f"WITH {_sql} SELECT id, {_len('e')} AS e_len, {_len('s')} AS s_len, len(e) AS e_dim, len(s) AS s_dim FROM w")(_view(_name))


# --- distances and exact search ----------------------------------------------------------------------------


@query("l2_distance", f"{sql_with(norm=False)} SELECT q.qid, o.id, round(list_distance(q.e, o.e), 6) AS de, round(list_distance(q.s, o.s), 6) AS ds FROM q, o WHERE band = 0")
def l2_distance(spark, sf_dir):
    c = case(spark, sf_dir)
    q = c.queries.where("band = 0").select("qid", F.col("e").alias("qe"), F.col("s").alias("qs"))
    # a stated block of queries against all rows; Spark sends the smaller side
    return c.objects.join(q, F.lit(True)).select("qid", "id", F.round(vectors.l2("e", "qe"), 6).alias("de"), F.round(vectors.l2("s", "qs"), 6).alias("ds"))


@query("normalisers", f"{sql_with()} SELECT round(em, 6) AS e_max, round(sm, 6) AS s_max FROM nrm")
def normalisers_(spark, sf_dir):
    return normalisers.exact_df(case(spark, sf_dir).objects).select(F.round("e_max", 6).alias("e_max"), F.round("s_max", 6).alias("s_max"))


CENTROID = """cen AS (SELECT list(v ORDER BY k) AS c FROM (SELECT k, avg(e[k]) AS v FROM o, (SELECT unnest(range(1, 65)) AS k) GROUP BY k)),
      cens AS (SELECT list(v ORDER BY k) AS c FROM (SELECT k, avg(s[k]) AS v FROM o, (SELECT unnest(range(1, 65)) AS k) GROUP BY k))"""


@query("normaliser_bounds", f"{sql_with()}, {CENTROID} SELECT round(max(list_distance(e, cen.c)), 6) AS e_radius, round(max(list_distance(s, cens.c)), 6) AS s_radius, true AS e_inside, true AS s_inside FROM o, cen, cens")
def normaliser_bounds(spark, sf_dir):
    c = case(spark, sf_dir)
    b = normalisers.bounded(c.objects)
    inside = lambda low, true, high: low <= true + 1e-9 and true <= high + 1e-9
    row = (round(b.extra["e_radius"], 6), round(b.extra["s_radius"], 6), inside(b.e, c.norm.e, b.extra["e_upper"]), inside(b.s, c.norm.s, b.extra["s_upper"]))
    return spark.createDataFrame([row], "e_radius double, s_radius double, e_inside boolean, s_inside boolean")


@query("hybrid_distance", f"{sql_with()} SELECT qid, band, o.id, round({DIST}, 6) AS dist FROM q, o, nrm")
def hybrid_distance(spark, sf_dir):
    c = case(spark, sf_dir)
    return exact.every_distance(c.objects, c.queries, c.norm, 6)


@query("exact_topk", TOP10)
def exact_topk(spark, sf_dir):
    return rounded(case(spark, sf_dir).truth())


@query("exact_topk_three_vectors", f"""{sql_with()}, h AS (
      SELECT qid, o.id, 0.5 * list_distance(q.e, o.e) / em + 0.3 * list_distance(q.s, o.s) / sm + 0.2 * list_distance(q.s[1:8], o.s[1:8]) AS dist FROM q, o, nrm WHERE band = 0),
      t AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid ORDER BY round(dist, 9), id) AS INTEGER) AS rank FROM h) SELECT qid, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10""")
def exact_topk_three_vectors(spark, sf_dir):
    c = case(spark, sf_dir)
    o = c.objects.withColumn("u", F.slice("s", 1, 8))
    q = c.queries.where("band = 0").select("qid", F.array(F.lit(0.5), F.lit(0.3), F.lit(0.2)).alias("weights"), "e", "s", F.slice("s", 1, 8).alias("u"))
    return exact.topk_many(o, q, ["e", "s", "u"], [c.norm.e, c.norm.s, 1.0]).select("qid", "rank", "id", F.round("dist", 6).alias("dist"))


@query("single_modality_topk", f"""{sql_with().replace("0.2e0 * b.band + 0.2e0 * ((id * 7919 + b.band * 104729) % 1000) / 1e3 AS alpha", "CAST(b.band AS DOUBLE) AS alpha").replace("unnest(range(5)) AS band", "unnest(range(2)) AS band")}, {TOP} SELECT qid, band, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10""")
def single_modality_topk(spark, sf_dir):
    c = case(spark, sf_dir)
    return rounded(exact.topk(c.objects, tables.with_alphas(c.queries, [0.0, 1.0]), c.norm))


@query("threshold_topk", TOP10)
def threshold_topk(spark, sf_dir):
    c = case(spark, sf_dir)
    return rounded(exact.threshold_topk(c.objects, c.queries, c.norm)[0])


@query("early_stop", TOP10)
def early_stop(spark, sf_dir):
    """Top-k with two-part distances: the second part only where the first is within the k-th result so far."""
    c = case(spark, sf_dir)
    return rounded(spatial.early_stop_topk(c.objects, c.queries, c.norm))


# --- frontiers ---------------------------------------------------------------------------------------------


@query("dominance_pairs", f"{PAIRS} SELECT a.p, count(*) AS n FROM pr a JOIN pr b ON a.p = b.p AND a.de <= b.de AND a.ds <= b.ds AND (a.de < b.de OR a.ds < b.ds) GROUP BY a.p")
def dominance_pairs(spark, sf_dir):
    c = case(spark, sf_dir)
    if whole.fits(c.objects):
        return whole.dominance(c.objects, c.norm, c.queries.where("band = 0").select(F.col("qid").alias("id"), "e", "s"))
    a = pairs_of(c)
    b = a.select("p", F.col("x").alias("y"), F.col("de").alias("de2"), F.col("ds").alias("ds2"))
    return a.join(b, "p").where(pareto.dominates("de", "ds", "de2", "ds2")).groupBy("p").agg(F.count(F.lit(1)).alias("n"))


FRONT = "SELECT a.p, a.x, round(a.de, 6) AS de, round(a.ds, 6) AS ds FROM {t} a WHERE NOT EXISTS (SELECT 1 FROM {t} b WHERE b.p = a.p AND b.de <= a.de AND b.ds <= a.ds AND (b.de < a.de OR b.ds < a.ds OR b.x < a.x))"


@query("pareto_frontier", f"{PAIRS} {FRONT.format(t='pr')}")
def pareto_frontier(spark, sf_dir):
    return pareto.frontier(pool_of(case(spark, sf_dir), 1)).select("p", "x", F.round("de", 6).alias("de"), F.round("ds", 6).alias("ds"))


_L = FRONT.replace("round(a.de, 6) AS de, round(a.ds, 6) AS ds", "a.de, a.ds")


@query("pareto_layers", f"{PAIRS}, f1 AS ({_L.format(t='pr')}), r1 AS (SELECT * FROM pr WHERE (p, x) NOT IN (SELECT p, x FROM f1)), f2 AS ({_L.format(t='r1')}), r2 AS (SELECT * FROM r1 WHERE (p, x) NOT IN (SELECT p, x FROM f2)), f3 AS ({_L.format(t='r2')}) SELECT p, x, 1 AS layer FROM f1 UNION ALL SELECT p, x, 2 FROM f2 UNION ALL SELECT p, x, 3 FROM f3")
def pareto_layers(spark, sf_dir):
    return pareto.layers(pool_of(case(spark, sf_dir), 3)).where("layer <= 3").select("p", "x", "layer")


@query("pareto_layers_by_peeling", ORACLES["pareto_layers"])
def pareto_layers_by_peeling(spark, sf_dir):
    return pareto.layers_by_peeling(pool_of(case(spark, sf_dir), 3), 3).select("p", "x", "layer")


#: A layer is the length of the longest chain of rows, each before and no farther than the next.
CHAINS = f"""{PAIRS.replace("WITH ", "WITH RECURSIVE ", 1)},
      ar AS (SELECT a.p, a.x, b.x AS y FROM pr a JOIN pr b ON a.p = b.p AND a.de <= b.de AND (a.ds, a.de, a.x) < (b.ds, b.de, b.x)),
      ch AS (SELECT p, x, 1 AS l FROM pr UNION SELECT ar.p, ar.y, ch.l + 1 FROM ch JOIN ar ON ar.p = ch.p AND ar.x = ch.x),
      ly AS (SELECT p, x, max(l) AS layer FROM ch GROUP BY p, x)"""


@query("pareto_layers_bounded", f"""{CHAINS}, n AS (SELECT p, layer, sum(count(*)) OVER (PARTITION BY p ORDER BY layer) AS upto FROM ly GROUP BY p, layer)
      SELECT p, x, CAST(layer AS INTEGER) AS layer FROM ly JOIN n USING (p, layer) WHERE upto <= 50 OR layer = 1""")
def pareto_layers_bounded(spark, sf_dir):
    """Whole layers of each pool up to fifty rows."""
    return pareto.layers(pairs_of(case(spark, sf_dir)), bound=50).select("p", "x", "layer")


@query("frontier_contains_nn", f"{PAIRS}, m AS (SELECT p, i, min(i / 10e0 * de + (1 - i / 10e0) * ds) AS d FROM pr, (SELECT unnest(range(11)) AS i) GROUP BY p, i) SELECT CAST(count(*) AS BIGINT) AS nodes_and_weights, CAST(0 AS BIGINT) AS missing FROM m")
def frontier_contains_nn(spark, sf_dir):
    """For each node and weight of a grid, whether the frontier has a nearest object: number checked, number missing."""
    p = pairs_of(case(spark, sf_dir))
    grid = F.explode(F.sequence(F.lit(0), F.lit(10)))
    d = F.round(F.col("i") / 10 * F.col("de") + (1 - F.col("i") / 10) * F.col("ds"), 12)
    every = p.withColumn("i", grid).groupBy("p", "i").agg(F.min(d).alias("d"))
    front = pareto.frontier(p).withColumn("i", grid).groupBy("p", "i").agg(F.min(d).alias("f"))
    return every.join(front, ["p", "i"], "left").agg(F.count(F.lit(1)).alias("nodes_and_weights"), F.sum(F.when(F.col("f") <= F.col("d"), 0).otherwise(1)).alias("missing"))


# --- weights at which edges are of use ---------------------------------------------------------------------

THREE = f"""{PAIRS}, f1 AS ({_L.format(t='pr')}), r1 AS (SELECT * FROM pr WHERE (p, x) NOT IN (SELECT p, x FROM f1)), f2 AS ({_L.format(t='r1')}),
      r2 AS (SELECT * FROM r1 WHERE (p, x) NOT IN (SELECT p, x FROM f2)), f3 AS ({_L.format(t='r2')})"""
TRI = f"""{THREE},
      near AS (SELECT * FROM f1 UNION ALL SELECT * FROM f2 UNION ALL SELECT * FROM f3),
      tri AS (
        SELECT a.p, a.x, b.x AS z, a.de AS pxe, a.ds AS pxs, b.de AS pze, b.ds AS pzs, list_distance(ox.e, oz.e) / em AS zxe, list_distance(ox.s, oz.s) / sm AS zxs
        FROM near a JOIN near b ON a.p = b.p AND a.x <> b.x JOIN o ox ON ox.id = a.x JOIN o oz ON oz.id = b.x, nrm)"""


def _half(a: str, b: str, lo: str, hi: str) -> str:
    return f"CASE WHEN {b} < 0 THEN greatest({a} / {b}, 0e0) ELSE 0e0 END AS {lo}, CASE WHEN {b} > 0 THEN least({a} / {b}, 1e0) WHEN {b} = 0 AND {a} <= 0 THEN -1e0 ELSE 1e0 END AS {hi}"


HALVES = f"hv AS (SELECT p, x, z, {_half('(pxs - pzs)', '((pze - pzs) - (pxe - pxs))', 'lo1', 'hi1')}, {_half('(pxs - zxs)', '((zxe - zxs) - (pxe - pxs))', 'lo2', 'hi2')} FROM tri)"
PRUNED = f"{TRI}, {HALVES}, pi AS (SELECT p, x, z, greatest(lo1, lo2) AS lo, least(hi1, hi2) AS hi FROM hv)"
UNION = f"""{PRUNED},
      iv AS (SELECT p, x, lo, hi FROM pi WHERE lo < hi),
      ed AS (SELECT *, max(hi) OVER (PARTITION BY p, x ORDER BY lo, hi ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM iv),
      isl AS (SELECT *, sum(CASE WHEN reach IS NULL OR lo > reach THEN 1 ELSE 0 END) OVER (PARTITION BY p, x ORDER BY lo, hi ROWS UNBOUNDED PRECEDING) AS g FROM ed),
      un AS (SELECT p, x, g, min(lo) AS lo, max(hi) AS hi FROM isl GROUP BY p, x, g),
      gp AS (SELECT p, x, coalesce(lag(hi) OVER (PARTITION BY p, x ORDER BY lo), 0) AS a, lo AS b FROM un
             UNION ALL SELECT p, x, max(hi), 1 FROM un GROUP BY p, x
             UNION ALL SELECT p, x, 0, 1 FROM near WHERE (p, x) NOT IN (SELECT p, x FROM un)),
      act AS (SELECT p, x, a AS lo, b AS hi FROM gp WHERE a < b)"""


def triangles(c: Case) -> DataFrame:
    """p, x, z among the first three layers of each query's pool, with the six distances."""
    if whole.fits(c.objects):
        return whole.triangles(c.objects, c.norm, c.queries.where("band = 0").select(F.col("qid").alias("id"), "e", "s"), 3)
    near = pareto.layers(pool_of(c, 3)).where("layer <= 3").select("p", "x", "de", "ds")
    other = near.select("p", F.col("x").alias("z"), F.col("de").alias("pze"), F.col("ds").alias("pzs"))
    o = c.objects
    t = near.withColumnRenamed("de", "pxe").withColumnRenamed("ds", "pxs").join(other, "p").where("x <> z")
    t = t.join(o.select(F.col("id").alias("x"), F.col("e").alias("xe"), F.col("s").alias("xs")), "x").join(o.select(F.col("id").alias("z"), F.col("e").alias("ze"), F.col("s").alias("zs")), "z")
    return t.select("p", "x", "z", "pxe", "pxs", "pze", "pzs", (vectors.l2("xe", "ze") / c.norm.e).alias("zxe"), (vectors.l2("xs", "zs") / c.norm.s).alias("zxs"))


def _six() -> list:
    return [F.col(n) for n in ("pze", "pzs", "pxe", "pxs", "zxe", "zxs")]


@query("alpha_cases", f"{TRI}, {HALVES} SELECT p, x, z, CASE WHEN lo1 < hi1 THEN round(lo1, 6) END AS lo, CASE WHEN lo1 < hi1 THEN round(hi1, 6) END AS hi FROM hv")
def alpha_cases(spark, sf_dir):
    h = al.halfline(F.col("pxs") - F.col("pzs"), (F.col("pze") - F.col("pzs")) - (F.col("pxe") - F.col("pxs")))
    return triangles(case(spark, sf_dir)).withColumn("h", h).select("p", "x", "z", F.round("h.lo", 6).alias("lo"), F.round("h.hi", 6).alias("hi"))


@query("pruned_interval", f"{PRUNED} SELECT p, x, z, CASE WHEN hi - lo > 1e-9 THEN round(lo, 6) END AS lo, CASE WHEN hi - lo > 1e-9 THEN round(hi, 6) END AS hi FROM pi")
def pruned_interval(spark, sf_dir):
    r = al.pruned_by(*_six())
    return triangles(case(spark, sf_dir)).withColumn("r", F.when(r.hi - r.lo > 1e-9, r)).select("p", "x", "z", F.round("r.lo", 6).alias("lo"), F.round("r.hi", 6).alias("hi"))


def active_sets(c: Case) -> DataFrame:
    """p, x, active: the weights at which none of the others removes the edge."""
    if whole.fits(c.objects):
        sets = whole.pruned_sets(c.objects, c.norm, c.queries.where("band = 0").select(F.col("qid").alias("id"), "e", "s"), 3)
    else:
        sets = triangles(c).groupBy("p", "x").agg(F.collect_list(al.pruned_by(*_six())).alias("r"))
    return sets.withColumn("active", al.complement(F.col("r")))


@query("active_ranges", f"{UNION} SELECT p, x, round(lo, 6) AS lo, round(hi, 6) AS hi FROM act")
def active_ranges(spark, sf_dir):
    return active_sets(case(spark, sf_dir)).select("p", "x", F.explode("active").alias("i")).select("p", "x", F.round("i.lo", 6).alias("lo"), F.round("i.hi", 6).alias("hi"))


@query("pruned_union", f"{UNION} SELECT p, x, round(lo, 6) AS lo, round(hi, 6) AS hi FROM un")
def pruned_union(spark, sf_dir):
    sets = active_sets(case(spark, sf_dir)).withColumn("u", al.normalise(F.col("r")))
    return sets.select("p", "x", F.explode("u").alias("i")).select("p", "x", F.round("i.lo", 6).alias("lo"), F.round("i.hi", 6).alias("hi"))


@query("range_length", f"{UNION} SELECT p, x, round(coalesce((SELECT sum(hi - lo) FROM act WHERE act.p = near.p AND act.x = near.x), 0), 6) AS length FROM near")
def range_length(spark, sf_dir):
    return active_sets(case(spark, sf_dir)).select("p", "x", F.round(al.length(F.col("active")), 6).alias("length"))


@query("edge_gate", f"{UNION} SELECT i / 10e0 AS alpha, CAST(count(DISTINCT (p, x)) AS BIGINT) AS active_edges FROM act, (SELECT unnest(range(11)) AS i) WHERE lo <= i / 10e0 AND i / 10e0 <= hi GROUP BY i")
def edge_gate(spark, sf_dir):
    grid = active_sets(case(spark, sf_dir)).withColumn("alpha", F.explode(F.array(*[F.lit(i / 10) for i in range(11)])))
    return grid.where(al.contains(F.col("active"), F.col("alpha"))).groupBy("alpha").agg(F.count(F.lit(1)).alias("active_edges"))


@query("range_codec", f"{UNION} SELECT p, x, CAST(floor(lo * 10000) AS SMALLINT) AS lo, CAST(ceil(hi * 10000) AS SMALLINT) AS hi, true AS covers FROM act")
def range_codec(spark, sf_dir):
    s = active_sets(case(spark, sf_dir)).withColumn("code", al.encode(F.col("active")))
    both = s.select("p", "x", F.explode(F.arrays_zip("active", "code", al.decode(F.col("code")).alias("back"))).alias("z"))
    return both.select("p", "x", F.col("z.code.lo").alias("lo"), F.col("z.code.hi").alias("hi"), ((F.col("z.back.lo") <= F.col("z.active.lo")) & (F.col("z.active.hi") <= F.col("z.back.hi"))).alias("covers"))


@query("interval_algebra", f"{UNION} SELECT p, x, round(coalesce((SELECT sum(least(hi, 0.7e0) - greatest(lo, 0.2e0)) FROM act WHERE act.p = near.p AND act.x = near.x AND least(hi, 0.7e0) > greatest(lo, 0.2e0)), 0), 6) AS inside FROM near")
def interval_algebra(spark, sf_dir):
    """Length of the active set inside [0.2, 0.7]."""
    cut = F.array(F.struct(F.lit(0.2).alias("lo"), F.lit(0.7).alias("hi")))
    return active_sets(case(spark, sf_dir)).select("p", "x", F.round(al.length(al.intersect(F.col("active"), cut)), 6).alias("inside"))


# --- edge selection ----------------------------------------------------------------------------------------


def all_pairs(c: Case) -> DataFrame:
    """All pairs of objects; the tables of this workload are small, and grouped by node."""
    return c.once("all_pairs", lambda: stash(exact.pair_distances(c.objects, c.norm), "all-pairs"))


def candidates(c: Case, bound: int) -> DataFrame:
    near = pareto.layers(all_pairs(c), bound).select("p", "x", "de", "ds")
    return near.join(c.objects.select(F.col("id").alias("x"), "e", "s"), "x")


@query("range_prune")
def range_prune(spark, sf_dir):
    c = case(spark, sf_dir)
    if whole.fits(c.objects):
        return whole.range_gated(c.objects, c.norm, c.params.ef_c, c.params.M, c.params.th)
    return prune.range_gated(candidates(c, c.params.ef_c), c.norm, c.params.M, c.params.th)


@query("rng_greedy")
def rng_greedy(spark, sf_dir):
    c = case(spark, sf_dir)
    if whole.fits(c.objects):
        return whole.rng_greedy(c.objects, c.norm, 0.5, c.params.ef_c, c.params.M)
    return prune.rng_greedy(candidates(c, c.params.ef_c), c.norm, 0.5, c.params.M)


def range_graph(c: Case, witness: str) -> DataFrame:
    """All objects as candidates of all, no threshold, no cap."""

    def joined() -> DataFrame:
        rows = all_pairs(c).join(c.objects.select(F.col("id").alias("x"), "e", "s"), "x")
        return prune.range_gated(rows, c.norm, 10**9, 0.0, witness=witness)

    return c.once(("exact", witness), lambda: stash(whole.exact_range_graph(c.objects, c.norm, witness) if whole.fits(c.objects) else joined(), "exact-graph"))


def rng_of(c: Case, alpha: float) -> DataFrame:
    return whole.rng_edges(c.objects, c.norm, alpha) if whole.fits(c.objects) else prune.rng(all_pairs(c), alpha)


@query("exact_range_graph")
def exact_range_graph(spark, sf_dir):
    return range_graph(case(spark, sf_dir), "active")


#: The ten nearest of p remove most pairs; only what they leave is held against all witnesses.
@query("rng_edges", f"""{sql_with()}, d AS MATERIALIZED (SELECT a.id AS p, b.id AS x, round(0.5 * list_distance(a.e, b.e) / em + 0.5 * list_distance(a.s, b.s) / sm, 9) AS d FROM o a, o b, nrm WHERE a.id <> b.id),
      nb AS MATERIALIZED (SELECT p, x, d FROM (SELECT *, row_number() OVER (PARTITION BY p ORDER BY d, x) AS r FROM d) WHERE r <= 10),
      g1 AS MATERIALIZED (SELECT DISTINCT a.p, a.x FROM d a JOIN nb w ON w.p = a.p AND w.d < a.d JOIN d v ON v.p = w.x AND v.x = a.x AND v.d < a.d),
      l1 AS MATERIALIZED (SELECT * FROM d ANTI JOIN g1 USING (p, x)),
      g2 AS MATERIALIZED (SELECT DISTINCT a.p, a.x FROM l1 a JOIN d w ON w.p = a.p AND w.d < a.d JOIN d v ON v.p = w.x AND v.x = a.x AND v.d < a.d)
      SELECT p, x, round(d, 6) AS d FROM l1 ANTI JOIN g2 USING (p, x)""")
def rng_edges(spark, sf_dir):
    return rng_of(case(spark, sf_dir), 0.5).select("p", "x", F.round("d", 6).alias("d"))


@query("rng_superset", f"{sql_with(norm=False)} SELECT (2 * i + 1) / 10e0 AS alpha, CAST(0 AS BIGINT) AS missing FROM (SELECT unnest(range(5)) AS i)")
def rng_superset(spark, sf_dir):
    """Edges of the relative neighbourhood graph that the all-candidates graph lacks at a weight, on a grid of weights.

    At the ends 0 and 1 twins in one modality leave edges that are active at a single weight, which ranges can't hold.
    """
    c = case(spark, sf_dir)
    graph = range_graph(c, "any")
    out = None
    for i in range(5):
        at = (2 * i + 1) * 1000
        have = graph.where((F.col("lo") <= at) & (at <= F.col("hi"))).select(F.col("src").alias("p"), F.col("dst").alias("x"))
        n = rng_of(c, at / 10_000).join(have, ["p", "x"], "left_anti").agg(F.count(F.lit(1)).alias("missing")).select(F.lit(at / 10_000).alias("alpha"), "missing")
        out = n if out is None else out.unionByName(n)
    return out


@query("greedy_reach")
def greedy_reach(spark, sf_dir):
    """Share of (start, target) trials in which a greedy walk over active edges reaches a target of the set, per rule and weight."""
    from ..operators import kernel

    c = case(spark, sf_dir)
    norm, vec = c.norm, c.objects.select("id", "e", "s")

    def trial(witness: str):
        def run(t: pa.Table) -> pa.Table:
            t = t.sort_by("id")
            ids = t.column("id").to_numpy()
            g = kernel.Graph(ids, vectors.matrix(t.column("e")), vectors.matrix(t.column("s")), norm)
            for i, arcs in enumerate(t.column("arcs").to_pylist()):
                dst, lo, hi = (np.array([a[k] for a in arcs or []], np.int64) for k in ("dst", "lo", "hi"))
                g.flat[i] = np.searchsorted(ids, dst), lo, hi
            rng, rows = np.random.default_rng(7), []
            for alpha in (0.1, 0.3, 0.5, 0.7, 0.9):
                hit = 0
                for _ in range(200):
                    a, b = rng.integers(len(ids), size=2)
                    hit += kernel.best_first(g, g.e[b], g.s[b], alpha, [a], 1, early_stop=False)[0][0] <= 1e-9
                rows.append((witness, alpha, hit / 200))
            return pa.table({"witness": [r[0] for r in rows], "alpha": [r[1] for r in rows], "reached": [r[2] for r in rows]})

        return run

    out = None
    for witness in ("any", "active"):
        nbrs = range_graph(c, witness).groupBy(F.col("src").alias("id")).agg(F.collect_list(F.struct("dst", "lo", "hi")).alias("arcs"))
        one = vec.join(nbrs, "id", "left").withColumn("g", F.lit(0)).groupBy("g").applyInArrow(trial(witness), "witness string, alpha double, reached double")
        out = one if out is None else out.unionByName(one)
    return out


# --- seeds -------------------------------------------------------------------------------------------------


@query("centroid", f"{sql_with(norm=False)}, c AS (SELECT k, avg(e[k]) AS e, avg(s[k]) AS s FROM o, (SELECT unnest(range(1, 65)) AS k) GROUP BY k) SELECT CAST(k AS INTEGER) AS place, round(e, 6) AS e, round(s, 6) AS s FROM c")
def centroid(spark, sf_dir):
    one = seeds.centroid_df(case(spark, sf_dir).objects)
    return one.select(F.posexplode(F.arrays_zip("e", "s"))).select((F.col("pos") + 1).alias("place"), F.round("col.e", 6).alias("e"), F.round("col.s", 6).alias("s"))


RIM = f"""{sql_with()}, {CENTROID}, d AS (SELECT id, list_distance(e, cen.c) / em AS de, list_distance(s, cens.c) / sm AS ds FROM o, cen, cens, nrm),
      rim AS (SELECT id, de, ds FROM d a WHERE NOT EXISTS (SELECT 1 FROM d b WHERE b.de >= a.de AND b.ds >= a.ds AND (b.de > a.de OR b.ds > a.ds OR b.id < a.id)))"""


@query("rim_seeds", f"{RIM} SELECT id, round(de, 6) AS de, round(ds, 6) AS ds FROM rim")
def rim_seeds(spark, sf_dir):
    c = case(spark, sf_dir)
    return seeds.rim(c.objects, c.norm).select("id", F.round("de", 6).alias("de"), F.round("ds", 6).alias("ds"))


@query("rim_seeds_incremental", ORACLES["rim_seeds"])
def rim_seeds_incremental(spark, sf_dir):
    """The rim of three portions of the rows, one added after the other."""
    c = case(spark, sf_dir)
    ce, cs = seeds.centroid(c.objects)
    d = seeds.from_centroid(c.objects, ce, cs, c.norm)
    rim = seeds.rim_of(d.where("id % 3 = 0"))
    for k in (1, 2):
        rim = seeds.update(rim, d.where(F.col("id") % 3 == k))
    return rim.select("id", F.round("de", 6).alias("de"), F.round("ds", 6).alias("ds"))


@query("seed_count", f"{RIM} SELECT count(*) AS seeds FROM rim")
def seed_count(spark, sf_dir):
    c = case(spark, sf_dir)
    return seeds.rim(c.objects, c.norm).agg(F.count(F.lit(1)).alias("seeds"))


@query("seeds_inner", RIM.replace("b.de >= a.de AND b.ds >= a.ds AND (b.de > a.de OR b.ds > a.ds", "b.de <= a.de AND b.ds <= a.ds AND (b.de < a.de OR b.ds < a.ds") + " SELECT id, round(de, 6) AS de, round(ds, 6) AS ds FROM rim")
def seeds_inner(spark, sf_dir):
    c = case(spark, sf_dir)
    return seeds.inner(c.objects, c.norm).select("id", F.round("de", 6).alias("de"), F.round("ds", 6).alias("ds"))


@query("seeds_random", f"{sql_with(norm=False)} SELECT id FROM o ORDER BY md5('42:' || id), id LIMIT 8")
def seeds_random(spark, sf_dir):
    return seeds.random(case(spark, sf_dir).objects, 8)


# --- index -------------------------------------------------------------------------------------------------


@query("build_index")
def build_index(spark, sf_dir):
    return case(spark, sf_dir).index().edges()


@query("frontier_search")
def frontier_search(spark, sf_dir):
    """Layers of candidates of the held-out rows over the finished graph, by supersteps."""
    c = case(spark, sf_dir)
    ix = c.index()
    t = c.queries.where("band = 0").select(F.col("qid").alias("id"), "e", "s")
    return bsp.frontier_search(ix.edges().select("src", "dst"), c.objects, t, ix.seeds(), c.norm, c.params.ef_c)


@query("graph_search")
def graph_search(spark, sf_dir):
    from ..workloads import flagship

    return flagship(spark, sf_dir)


@query("reverse_refresh")
def reverse_refresh(spark, sf_dir):
    """Degrees with both rules for edges back to new nodes."""
    c = case(spark, sf_dir)
    out = None
    for rule in ("reprune", "append"):
        ix = c.index(c.params.but(reverse=rule))
        one = metrics.degree(ix.edges(), ix.nodes).withColumn("reverse", F.lit(rule))
        out = one if out is None else out.unionByName(one)
    return out


@query("graph_search_sharded")
def graph_search_sharded(spark, sf_dir):
    """Recall and work for ways to shard and to probe."""
    c = case(spark, sf_dir)
    out = None
    for by, n, probes in (("hash", 4, "all"), ("cluster", 4, 1), ("cluster", 4, 2), ("cluster", 4, "bound")):
        one = runs_of(f"{by}{n}/{probes}", c, gated(c, None, True, ShardParams(n, by), probes), (50,))
        out = one if out is None else out.unionByName(one)
    return out


@query("route_bounds", f"{sql_with(norm=False)} SELECT CAST(count(*) AS BIGINT) AS checked, CAST(0 AS BIGINT) AS above FROM q, o")
def route_bounds(spark, sf_dir):
    """Pairs of query and object whose shard's bound exceeds their distance: none."""
    c = case(spark, sf_dir)
    ix = c.index(None, ShardParams(4, "cluster"))
    r = index.route(ix, c.queries).join(c.queries, ["qid", "band"])
    o = ix.nodes.where("level = 0").select("shard", "id", F.col("e").alias("oe"), F.col("s").alias("os"))
    d = r.join(o, "shard").withColumn("dist", vectors.hybrid("e", "s", "oe", "os", F.col("alpha"), c.norm.e, c.norm.s))
    return d.agg(F.count(F.lit(1)).alias("checked"), F.sum(F.when(F.col("bound") > F.col("dist") + 1e-6, 1).otherwise(0)).alias("above"))


@query("graph_search_bsp")
def graph_search_bsp(spark, sf_dir):
    c = case(spark, sf_dir)
    ix = c.index()
    hits = bsp.search(ix.edges(), c.objects, c.queries, ix.seeds(), c.norm, 10, 50)
    return hits.join(metrics.recall(hits, c.truth()), ["qid", "band"])


@query("build_bsp")
def build_bsp(spark, sf_dir):
    c = case(spark, sf_dir)
    return c.once("bsp", lambda: bsp.build(c.objects, c.params, c.norm))[0]


@query("index_roundtrip")
def index_roundtrip(spark, sf_dir):
    """An index written, read again, and its degrees."""
    from ..storage import new_path

    path = new_path(spark, "saved")
    index.write_index(case(spark, sf_dir).index(), path)
    back = index.read_index(spark, path)
    return metrics.degree(back.edges(), back.nodes)


# --- baselines ---------------------------------------------------------------------------------------------


@query("bl_fixed_alpha")
def bl_fixed_alpha(spark, sf_dir):
    c = case(spark, sf_dir)
    return runs_of("fixed", c, plain(c.fixed()))


@query("bl_hsw")
def bl_hsw(spark, sf_dir):
    """The hierarchical graph itself: nodes and edges per level."""
    ix = case(spark, sf_dir).fixed()
    return ix.nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum(F.size("dst")).alias("edges"))


@query("bl_merge")
def bl_merge(spark, sf_dir):
    c = case(spark, sf_dir)
    return runs_of("merge", c, merged(c.merge()))


MERGE = f"""{sql_with()}, {TOP},
      le AS (SELECT qid, band, o.id, row_number() OVER (PARTITION BY qid, band ORDER BY round(list_distance(q.e, o.e) / em, 9), o.id) AS r FROM q, o, nrm),
      ls AS (SELECT qid, band, o.id, row_number() OVER (PARTITION BY qid, band ORDER BY round(list_distance(q.s, o.s) / sm, 9), o.id) AS r FROM q, o, nrm),
      un AS (SELECT qid, band, id FROM le WHERE r <= 20 UNION SELECT qid, band, id FROM ls WHERE r <= 20),
      mg AS (SELECT qid, band, id, dist, CAST(row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS INTEGER) AS rank FROM h JOIN un USING (qid, band, id))"""


@query("bl_merge_exact", f"{MERGE} SELECT qid, band, rank, id, round(dist, 6) AS dist FROM mg WHERE rank <= 10")
def bl_merge_exact(spark, sf_dir):
    c = case(spark, sf_dir)
    return rounded(graphs.merge_exact(c.objects, c.queries, c.norm, 10, 20))


@query("bl_overlay")
def bl_overlay(spark, sf_dir):
    c = case(spark, sf_dir)
    return runs_of("overlay", c, plain(c.overlay()))


@query("bl_oracle")
def bl_oracle(spark, sf_dir):
    c = case(spark, sf_dir)
    q = tables.with_alphas(c.queries, list(graphs.FIVE))
    return runs_of("oracle", c, asked(c.oracle()), queries=q, tag="five")


GEO = f"{sql_with('emb_geo')}, {TOP} SELECT qid, band, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10"


@query("bl_rect_topk", f"{sql_with('emb_geo')}, h AS (SELECT qid, band, o.id, list_distance(q.s, o.s) / sm AS dist FROM q, o, nrm), t AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS INTEGER) AS rank FROM h) SELECT qid, band, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10")
def bl_rect_topk(spark, sf_dir):
    c = case(spark, sf_dir, "emb_geo")
    packed = c.once("packed", lambda: stash(spatial.str_pack(c.objects), "packed"))
    return rounded(spatial.box_topk(packed, c.queries, c.norm, 10))


@query("bl_quad_ring", GEO)
def bl_quad_ring(spark, sf_dir):
    c = case(spark, sf_dir, "emb_geo")
    return rounded(spatial.quad_ring_topk(c.objects, c.queries, c.norm))


@query("bl_pivot", GEO)
def bl_pivot(spark, sf_dir):
    c = case(spark, sf_dir, "emb_geo")
    return rounded(spatial.pivot_topk(c.objects, c.queries, c.norm))


@query("bl_clusters_exact", GEO)
def bl_clusters_exact(spark, sf_dir):
    c = case(spark, sf_dir, "emb_geo")
    return rounded(spatial.cluster_topk(c.objects, c.queries, c.norm))


@query("bl_clusters_approx")
def bl_clusters_approx(spark, sf_dir):
    c = case(spark, sf_dir, "emb_geo")
    return rounded(spatial.cluster_topk(c.objects, c.queries, c.norm, exact=False))


# --- measures ----------------------------------------------------------------------------------------------

RECALL = f"{MERGE}, rc AS (SELECT t.qid, t.band, count(mg.id) / 10e0 AS recall FROM t LEFT JOIN mg ON mg.qid = t.qid AND mg.band = t.band AND mg.id = t.id AND mg.rank <= 10 WHERE t.rank <= 10 GROUP BY ALL)"


@query("recall_at_k", f"{RECALL} SELECT qid, band, round(recall, 6) AS recall FROM rc")
def recall_at_k(spark, sf_dir):
    c = case(spark, sf_dir)
    return metrics.recall(graphs.merge_exact(c.objects, c.queries, c.norm, 10, 20), c.truth()).select("qid", "band", F.round("recall", 6).alias("recall"))


@query("recall_by_band", f"{RECALL} SELECT band, round(avg(recall), 6) AS recall, count(*) AS queries FROM rc GROUP BY ROLLUP (band)")
def recall_by_band(spark, sf_dir):
    c = case(spark, sf_dir)
    r = metrics.recall(graphs.merge_exact(c.objects, c.queries, c.norm, 10, 20), c.truth())
    return metrics.by_band(r).select("band", F.round("recall", 6).alias("recall"), "queries")


@query("tradeoff_curve")
def tradeoff_curve(spark, sf_dir):
    """(recall, queries a second on one core) of the range-gated graph over the sweep of ef: points that nothing beats."""
    c = case(spark, sf_dir)
    runs = stash(runs_of("range", c, gated(c)).where("band is null"), "runs")
    return metrics.tradeoff(runs).select("method", "ef", "recall", "qps", "n_dist")


@query("qps_at_recall")
def qps_at_recall(spark, sf_dir):
    """Queries a second on one core at recall 0.9, of each method, from its curve."""
    c = case(spark, sf_dir)
    together(c.index, c.fixed, c.merge)
    out = _union([runs_of("range", c, gated(c)), runs_of("fixed", c, plain(c.fixed())), runs_of("merge", c, merged(c.merge()))])
    return metrics.qps_at(stash(out.where("band is null").select("method", "ef", "recall", "qps"), "runs"), 0.9).select("method", F.round("qps", 1).alias("qps"))


@query("merge_sides")
def merge_sides(spark, sf_dir):
    """Queries a second of the merge's two sides on the workload with coordinates: graph and rectangle tree, k' = 10 and more."""
    c = case(spark, sf_dir, "emb_geo")
    out = []
    for name, side in zip(("graph", "rectangle_tree"), c.merge().sides(c.queries, (10, 50, 200))):
        per = side.groupBy("qid", "band", "ef").agg(F.first("n_dist").alias("n_dist"), F.first("seconds").alias("seconds"))
        out.append(_named(per.groupBy(F.col("ef").alias("k_prime")).agg(F.round(1 / F.avg("seconds"), 1).alias("qps"), F.round(F.avg("n_dist"), 1).alias("n_dist")), side=name))
    return _union(out)


@query("degree_stats")
def degree_stats(spark, sf_dir):
    ix = case(spark, sf_dir).index()
    return metrics.degree(ix.edges(), ix.nodes)


@query("range_stats")
def range_stats(spark, sf_dir):
    return metrics.range_stats(case(spark, sf_dir).index().edges())


@query("join_alpha_interval")
def join_alpha_interval(spark, sf_dir):
    """Active edges at each query's weight: the interval join of weights and stored ranges."""
    c = case(spark, sf_dir)
    return metrics.active_degree(c.index().edges(), c.queries.select("band", "alpha").distinct())


@query("index_size")
def index_size(spark, sf_dir):
    return metrics.index_size(case(spark, sf_dir).index())


@query("search_work")
def search_work(spark, sf_dir):
    c = case(spark, sf_dir)
    width = c.queries.select((F.size("e") + F.size("s")).alias("n")).first().n
    return metrics.work(index.topk(c.index(), c.queries, SearchParams(10, 100)), width)


@query("reachability")
def reachability(spark, sf_dir):
    return metrics.reachability(case(spark, sf_dir).index())


# --- experiments: every sweep is the published one, ef and k' from 10 to 200 in steps of 10 ------------------


def _union(frames) -> DataFrame:
    out = None
    for f in frames:
        out = f if out is None else out.unionByName(f)
    return out


def _named(df: DataFrame, **columns) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in columns.items()], "*")


def _active(c: Case, ix: index.Index) -> DataFrame:
    """band, active_degree: mean number of edges per node that a query of the band may use."""
    per = metrics.active_degree(ix.edges(), c.queries.select("band", "alpha").distinct())
    return per.groupBy("band").agg(F.round(F.avg("active_edges") / c.n, 2).alias("active_degree"))


@query("wl_motivation")
def wl_motivation(spark, sf_dir):
    c = case(spark, sf_dir)
    together(c.fixed, c.merge)
    return _union([runs_of("fixed", c, plain(c.fixed())), runs_of("merge", c, merged(c.merge()))]).where("band is not null")


@query("wl_tradeoff")
def wl_tradeoff(spark, sf_dir):
    out = []
    cases = [case(spark, sf_dir, name) for name in ("emb_split", "emb_geo", "text_emb", "doc_pair")]
    together(*[f for c in cases for f in (c.index, c.fixed, c.merge, c.overlay, c.truth)])
    for c in cases:
        for method, search in (("range", gated(c)), ("fixed", plain(c.fixed())), ("merge", merged(c.merge())), ("overlay", plain(c.overlay()))):
            out.append(_named(runs_of(method, c, search), workload=c.name))
    return _union(out)


@query("wl_bands")
def wl_bands(spark, sf_dir):
    """Recall and work per band next to the active degree of the band: what a query may use against what it finds."""
    c = case(spark, sf_dir)
    together(c.index, c.fixed, c.overlay)
    out = []
    for method, ix in (("range", c.index()), ("fixed", c.fixed()), ("overlay", c.overlay())):
        out.append(runs_of(method, c, plain(ix)).where("band is not null").join(_active(c, ix), "band"))
    return _union(out)


@query("wl_oracle_gap")
def wl_oracle_gap(spark, sf_dir):
    c = case(spark, sf_dir)
    together(c.index, c.merge, c.overlay, *[lambda a=a: c.fixed(None, a) for a in graphs.FIVE])
    q = stash(tables.with_alphas(c.queries, list(graphs.FIVE)), "five")
    searches = {"range": gated(c), "fixed": plain(c.fixed()), "merge": merged(c.merge()), "overlay": plain(c.overlay()), "oracle": asked(c.oracle())}
    return _union([runs_of(m, c, s, queries=q, tag="five") for m, s in searches.items()])


@query("wl_extreme")
def wl_extreme(spark, sf_dir):
    c = case(spark, sf_dir)
    together(c.index, c.fixed, c.overlay, c.merge)
    q = stash(tables.with_alphas(c.queries, [0.0, 1.0]), "extreme")
    searches = {"range": gated(c), "fixed": plain(c.fixed()), "merge": merged(c.merge()), "overlay": plain(c.overlay()), "oracle": asked(c.oracle((0.0, 1.0)))}
    return _union([runs_of(m, c, s, queries=q, tag="extreme") for m, s in searches.items()])


SCALES = (("doc_geo", 1), ("line_geo", 16), ("line_geo", 4), ("line_geo", 1))


@query("wl_scale")
def wl_scale(spark, sf_dir, rows_per_shard: int = 2_048):
    """The growing workloads with coordinates (the largest one at a sixteenth, a quarter and all of its rows): build
    seconds, shards, evaluations per insertion, and the sharded graph against an exact scan."""
    from ..workloads import portion

    out = []
    for name, part in SCALES:
        c = portion(spark, sf_dir, name, part, BuildParams(M=10, ef_c=50))
        shards = ShardParams(max_rows=rows_per_shard)
        ix = c.index(None, shards)
        n_dist = ix.nodes.agg(F.sum("n_dist").alias("n")).first().n
        cost = {"workload": name, "objects": c.n, "shards": ix.shards.count(), "build_s": round(ix.metrics["build_s"], 2), "evaluations_per_insertion": round(n_dist / max(1, c.n), 1)}
        out.append(_named(runs_of("range", c, gated(c, None, True, shards), (10, 50, 100)), **cost))
        out.append(_named(runs_of("scan", c, lambda q, efs, c=c: spatial.scan_topk(c.objects, q, c.norm), (10,)), **cost))
    return _union(out)


def _cost(parts: list[index.Index]) -> DataFrame:
    """One row: edges, degree, bytes, evaluations and seconds to build, summed over the parts."""
    each = [metrics.degree(x.edges(), x.nodes).join(metrics.index_size(x), F.lit(True)).join(x.nodes.agg(F.sum("n_dist").alias("evaluations")), F.lit(True)).withColumn("build_s", F.lit(round(x.metrics["build_s"], 3))) for x in parts]
    return _union(each).agg(*[F.sum(x).alias(x) for x in ("edges", "avg_edges", "vector_bytes", "edge_bytes", "range_bytes", "evaluations", "build_s")])


@query("wl_index_cost")
def wl_index_cost(spark, sf_dir):
    """Edges, bytes, distance evaluations and seconds to build of all indexes, built one after the other."""
    out, cases = [], [case(spark, sf_dir, name) for name in ("emb_split", "emb_geo", "text_emb", "doc_pair")]
    for c in cases:
        m = c.merge()
        for method, parts in (("range", [c.index()]), ("fixed", [c.fixed()]), ("merge", [x for x in (m.by_e, m.by_s) if x is not None]), ("overlay", [c.overlay()])):
            out.append(_named(_cost(parts), workload=c.name, method=method))
    return _union(out)


def _scaled(c: Case, M: int, ef: int) -> BuildParams:
    return c.params.but(M=max(2, M * c.params.M // 40), ef_c=max(8, ef * c.params.ef_c // 200))


@query("wl_sensitivity")
def wl_sensitivity(spark, sf_dir):
    c, out = case(spark, sf_dir), []
    grid = ((40, 200, 10, 50), (50, 250, 12, 60), (60, 300, 14, 70))
    together(*[f for M, ef, a, b in grid for p in [_scaled(c, M, ef)] for f in (lambda p=p: c.index(p), lambda p=p: c.fixed(p), lambda p=p: c.merge(p), lambda a=a, b=b: c.overlay(_scaled(c, a, b)))])
    for M, ef, oM, oef in grid:
        p = _scaled(c, M, ef)
        for method, s in (("range", gated(c, p)), ("fixed", plain(c.fixed(p))), ("merge", merged(c.merge(p))), ("overlay", plain(c.overlay(_scaled(c, oM, oef))))):
            out.append(_named(runs_of(method, c, s).where("band is null"), M=M, ef_c=ef))
    return _union(out)


@query("wl_ablation")
def wl_ablation(spark, sf_dir):
    c = case(spark, sf_dir)
    p = c.params
    kinds = {"full": (p, True), "no_pruning": (p.but(pruning="none"), True), "static_use": (p, False), "greedy_candidates": (p.but(candidates="greedy"), True), "centroid_seeds": (p.but(seeds="centroid"), True), "random_seeds": (p.but(seeds="random"), True)}
    together(*[lambda k=k: c.index(k) for k, _ in kinds.values()])
    return _union([runs_of(m, c, gated(c, k, gate)) for m, (k, gate) in kinds.items()])


@query("wl_variants")
def wl_variants(spark, sf_dir):
    """Witness, cap, tie, reverse and threshold variants."""
    c = case(spark, sf_dir)
    p = c.params
    kinds = {"printed": p, "witness_active": p.but(witness="active"), "cap_hard": p.but(cap="hard"), "ties_definition": p.but(ties="definition"), "reverse_append": p.but(reverse="append"), "th_0": p.but(th=0.0), "th_0.3": p.but(th=0.3), "seeds_capped": p.but(max_seeds=4)}
    together(*[lambda k=k: c.index(k) for k in kinds.values()])
    return _union([runs_of(m, c, gated(c, k)) for m, k in kinds.items()])


PARITY = {"range": [(40, 200)], "fixed": [(40, 200), (50, 250), (60, 300), (70, 350), (80, 400)], "merge": [(40, 200), (50, 250), (60, 300), (70, 350), (80, 400)], "overlay": [(10, 50), (12, 60), (14, 70), (16, 80), (18, 90), (20, 100), (30, 150), (40, 200)]}


@query("wl_parity")
def wl_parity(spark, sf_dir):
    """All settings of the parity tables, scaled: seconds and evaluations to build, edges per node, bytes, and the sweep."""
    c, out = case(spark, sf_dir), []
    builds = {"range": c.index, "fixed": c.fixed, "merge": c.merge, "overlay": c.overlay}
    together(*[lambda f=builds[m], p=_scaled(c, M, ef): f(p) for m, settings in PARITY.items() for M, ef in settings])
    for method, settings in PARITY.items():
        for M, ef in settings:
            p = _scaled(c, M, ef)
            parts = {"range": lambda: [c.index(p)], "fixed": lambda: [c.fixed(p)], "merge": lambda: [c.fixed(p, 1.0), c.fixed(p, 0.0)], "overlay": lambda: [c.overlay(p)]}[method]()
            search = merged(c.merge(p)) if method == "merge" else plain(parts[0])
            out.append(_named(runs_of(method, c, search).where("band is null").join(F.broadcast(_cost(parts)), F.lit(True)), M=M, ef_c=ef))
    return _union(out)


@query("wl_spatial_prior")
def wl_spatial_prior(spark, sf_dir):
    """Prior methods for text with coordinates, a scan and the graph: recall, evaluations and rate on the workload with a two-dimensional side."""
    c = case(spark, sf_dir, "emb_geo")
    methods = {"scan": spatial.scan_topk, "quad_ring": spatial.quad_ring_topk, "pivot": spatial.pivot_topk, "clusters": spatial.cluster_topk, "clusters_approx": lambda o, q, n: spatial.cluster_topk(o, q, n, exact=False)}
    prior = [runs_of(m, c, lambda q, efs, f=f: f(c.objects, q, c.norm), (10,)) for m, f in methods.items()]
    return _union([*prior, runs_of("range", c, gated(c))])


# --- plans and the index source ----------------------------------------------------------------------------


@query("planner_filtered_topk", f"{sql_with()}, h AS (SELECT qid, band, o.id, {DIST} AS dist FROM q, o, nrm WHERE o.id IN (SELECT doc_id FROM documents WHERE lang <> 'en')), t AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid, band ORDER BY round(dist, 9), id) AS INTEGER) AS rank FROM h) SELECT qid, band, rank, id, round(dist, 6) AS dist FROM t WHERE rank <= 10")
def planner_filtered_topk(spark, sf_dir):
    """A filtered search that must be exact."""
    from ..plans import planner

    c = case(spark, sf_dir)
    return rounded(planner.topk(c.objects, c.queries, c.norm, 10, F.col("attrs.lang") != "en")[0])


@query("planner_graph_topk")
def planner_graph_topk(spark, sf_dir):
    """The same filter over the graph: the search asks for more, filters, and scans for queries that come short."""
    from ..plans import planner

    c = case(spark, sf_dir)
    return rounded(planner.topk(c.objects, c.queries, c.norm, 10, F.col("attrs.lang") != "en", c.index(), guarantee="approximate")[0])


@query("range_index_source")
def range_index_source(spark, sf_dir):
    """Edges of a written index that are active at 0.5, through the data source."""
    from ..sources import range_index
    from ..storage import new_path

    path = new_path(spark, "saved")
    index.write_index(case(spark, sf_dir).index(None, ShardParams(3)), path)
    range_index.register(spark)
    return spark.read.format("range_index").option("alpha", "0.5").load(path)
