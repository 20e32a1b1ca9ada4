"""Given tables, and the two-vector workloads made from them.

objects: id, e, s and attributes; queries: the rows with id % 20 = 7, held out, five weights each, one per band.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str) -> None:
    """Temporary views of all given tables, for SQL."""
    for n in NAMES:
        load(spark, sf_dir, n).createOrReplaceTempView(n)


def bucket_vector(docs: DataFrame, width: int, odd: bool | None = None) -> DataFrame:
    """id, v: tokens of text counted by md5 bucket, scaled to length 1. odd: only odd or only even places."""
    tokens = F.filter(F.split("text", "\\s+"), lambda t: t != "")
    if odd is not None:
        tokens = F.filter(tokens, lambda t, i: (i % 2 == 0) if odd else (i % 2 == 1))
    bucket = F.conv(F.substring(F.md5(F.col("t")), 1, 4), 16, 10).cast("int") % width
    counts = docs.select(F.col("doc_id").alias("id"), F.explode_outer(tokens).alias("t")).groupBy("id", bucket.alias("k")).agg(F.count("t").alias("n"))
    per = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.when(F.col("k").isNotNull(), F.struct("k", "n")))).alias("m"), F.sqrt(F.sum(F.col("n") * F.col("n"))).alias("len"))
    value = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.coalesce(F.element_at(F.col("m"), i) / F.nullif(F.col("len"), F.lit(0.0)), F.lit(0.0)).cast("float"))
    return per.select("id", value.alias("v"))


def coordinate(id_: Column, nation: Column) -> Column:
    """A place in one of 25 towns."""
    x = nation % 5 + ((id_ * 7919) % 1000) / F.lit(2500.0)
    y = F.floor(nation / 5) + ((id_ * 104729) % 1000) / F.lit(2500.0)
    return F.array(x.cast("float"), y.cast("float"))


def emb_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.slice("embedding", 1, 32).alias("e"), F.slice("embedding", 33, 32).alias("s"), F.struct("label").alias("attrs"))


def emb_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    emb, cust = load(spark, sf_dir, "embeddings"), load(spark, sf_dir, "customer")
    return emb.join(cust, emb.vec_id == cust.c_custkey).select(F.col("vec_id").alias("id"), F.col("embedding").alias("e"), coordinate(F.col("vec_id"), F.col("c_nationkey")).alias("s"), F.struct("label", "c_nationkey", "c_mktsegment").alias("attrs"))


def text_emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, emb = load(spark, sf_dir, "documents"), load(spark, sf_dir, "embeddings")
    both = docs.join(emb, docs.doc_id == emb.vec_id)
    vec = bucket_vector(both.select("doc_id", "text"), 64)
    return vec.join(both, vec.id == both.doc_id).select("id", F.col("v").alias("e"), F.col("embedding").alias("s"), F.struct("lang", "source", "n_chars").alias("attrs"))


def doc_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    a, b = bucket_vector(docs, 64, True), bucket_vector(docs, 32, False).withColumnRenamed("v", "w")
    none = F.transform(F.sequence(F.lit(1), F.lit(32)), lambda i: F.lit(0.0).cast("float"))
    return a.join(b, "id", "left").join(docs.withColumnRenamed("doc_id", "id"), "id").select("id", F.col("v").alias("e"), F.coalesce("w", none).alias("s"), F.struct("lang", "source").alias("attrs"))


def doc_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, cust = load(spark, sf_dir, "documents"), load(spark, sf_dir, "customer")
    both = docs.join(cust, docs.doc_id == cust.c_custkey)
    vec = bucket_vector(both.select("doc_id", "text"), 64)
    return vec.join(both, vec.id == both.doc_id).select("id", F.col("v").alias("e"), coordinate(F.col("id"), F.col("c_nationkey")).alias("s"), F.struct("lang", "c_nationkey").alias("attrs"))


def line_geo(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items: numeric features by their deviations, and (ship day, part size)."""
    li, part = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "part").select("p_partkey", "p_size")
    numbers = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    stats = li.agg(*[f(c).alias(f"{n}_{c}") for c in numbers for n, f in (("m", F.avg), ("d", F.stddev_pop))]).first()
    copy = Window.partitionBy("l_orderkey", "l_linenumber").orderBy(*[c for c in li.columns if c not in ("l_orderkey", "l_linenumber")])
    flags = [F.when(F.col("l_returnflag") == v, 1.0).otherwise(0.0) for v in ("A", "N", "R")] + [F.when(F.col("l_linestatus") == v, 1.0).otherwise(0.0) for v in ("O", "F")]
    e = F.array(*[((F.col(c) - stats[f"m_{c}"]) / (stats[f"d_{c}"] or 1.0)).cast("float") for c in numbers], *[f.cast("float") for f in flags])
    s = F.array(F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")).cast("float"), F.col("p_size").cast("float"))
    rows = li.withColumn("copy", F.row_number().over(copy)).join(part, li.l_partkey == part.p_partkey)
    return rows.select(((F.col("l_orderkey") * 8 + F.col("l_linenumber")) * 64 + F.col("copy")).cast("long").alias("id"), e.alias("e"), s.alias("s"), F.struct("l_orderkey").alias("attrs"))


def event_features(events: DataFrame) -> DataFrame:
    """Works on batches and on streams."""
    kinds = [F.when(F.col("event_type") == v, 1.0).otherwise(0.0) for v in EVENT_TYPES]
    k = F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0))
    e = F.array(*[x.cast("float") for x in [*kinds, F.log1p(F.coalesce("value", F.lit(0.0))), k / 100, (F.col("user_id") % 10) / 10]])
    s = F.array(F.hour("ts").cast("float"), F.dayofmonth("ts").cast("float"))
    return events.select(F.col("event_id").alias("id"), e.alias("e"), s.alias("s"), F.struct("ts", "user_id").alias("attrs"))


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_features(load(spark, sf_dir, "events"))


WORKLOADS = {"emb_split": emb_split, "emb_geo": emb_geo, "text_emb": text_emb, "doc_pair": doc_pair, "doc_geo": doc_geo, "line_geo": line_geo, "event_stream": event_stream}


def alpha_of(id_: Column, band: Column) -> Column:
    return F.lit(0.2) * band + F.lit(0.2) * ((id_ * 7919 + band * 104729) % 1000) / F.lit(1000.0)


def held_out(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(objects, queries) of a workload."""
    objects = rows.where("id % 20 <> 7")
    q = rows.where("id % 20 = 7").select(F.col("id").alias("qid"), "e", "s").withColumn("band", F.explode(F.sequence(F.lit(0), F.lit(4))))
    return objects, q.select("qid", "band", alpha_of(F.col("qid"), F.col("band")).alias("alpha"), "e", "s")


def with_alphas(queries: DataFrame, alphas: list[float]) -> DataFrame:
    """Other weights for the same vectors; band counts them."""
    one = queries.where("band = 0").select("qid", "e", "s")
    each = F.explode(F.arrays_zip(F.sequence(F.lit(0), F.lit(len(alphas) - 1)).alias("band"), F.array(*map(F.lit, alphas)).alias("alpha")))
    return one.withColumn("z", each).select("qid", F.col("z.band").alias("band"), F.col("z.alpha").alias("alpha"), "e", "s")
