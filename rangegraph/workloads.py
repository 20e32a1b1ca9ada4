"""Workloads with their queries, normalisers, truth and indexes, and the flagship query. Shared by queries, tests and bench."""

from __future__ import annotations

from functools import cached_property
from threading import Lock

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines import graphs
from .baselines.graphs import at_once as together
from .operators import exact, index, metrics, normalisers
from .schema import BuildParams, Norm, SearchParams, ShardParams
from .sources import tables
from .storage import stash

#: Half the published M and ef_construction, at every size of table.
HALVED = BuildParams(M=20, ef_c=100)
#: The published sweep of ef_search and k'.
SWEEP = tuple(range(10, 201, 10))

_cases: dict[tuple, "Case"] = {}


def case(spark: SparkSession, sf_dir: str, name: str = "text_emb") -> "Case":
    """A workload on the given tables, made once per application."""
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _cases:
        _cases[key] = Case(spark, sf_dir, name)
    return _cases[key]


class Case:
    """A workload: objects, queries, normalisers, truth and indexes, each made when first asked for."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, params: BuildParams = HALVED):
        self.spark, self.sf_dir, self.name, self.params = spark, sf_dir, name, params
        rows = stash(tables.WORKLOADS[name](spark, sf_dir), name)
        objects, queries = tables.held_out(rows)
        self.objects, self.queries = objects, stash(queries, "queries")
        self._indexes: dict = {}
        self._lock = Lock()
        self._truth: dict = {}

    @cached_property
    def n(self) -> int:
        return self.objects.count()

    @cached_property
    def flat(self) -> bool:
        """Whether s has two dimensions."""
        row = self.objects.select(F.size("s").alias("n")).first()
        return row is not None and row.n == 2

    @cached_property
    def norm(self) -> Norm:
        with self._lock:
            return self._norm

    @cached_property
    def _norm(self) -> Norm:
        """The true normalisers at every size; larger tables leave out objects near the centroid first, which gives the same."""
        return normalisers.exact(self.objects) if self.n <= 20_000 else normalisers.pruned(self.objects)

    def truth(self, k: int = 10, queries: DataFrame | None = None, tag: str = "bands") -> DataFrame:
        if (k, tag) not in self._truth:
            self._truth[k, tag] = stash(exact.topk(self.objects, self.queries if queries is None else queries, self.norm, k), "truth")
        return self._truth[k, tag]

    def once(self, key, make):
        if key not in self._indexes:
            self._indexes[key] = make()
        return self._indexes[key]

    def index(self, params: BuildParams | None = None, shards: ShardParams = ShardParams()) -> index.Index:
        p = params or self.params
        return self.once(("range", p, shards), lambda: index.build_index(self.objects, p, self.norm, shards))

    def fixed(self, params: BuildParams | None = None, alpha0: float = 0.5) -> index.Index:
        p = params or self.params
        return self.once(("fixed", p, alpha0), lambda: graphs.fixed_alpha(self.objects, p, self.norm, alpha0))

    def merge(self, params: BuildParams | None = None) -> graphs.Merge:
        p = params or self.params
        by_e, by_s = together(lambda: self.fixed(p, 1.0), lambda: None if self.flat else self.fixed(p, 0.0))
        return graphs.Merge(by_e, by_s, self.objects, self.norm)

    def overlay(self, params: BuildParams | None = None) -> index.Index:
        p = params or self.params.but(M=max(4, self.params.M // 4), ef_c=max(16, self.params.ef_c // 4))
        return self.once(("overlay", p), lambda: graphs.overlay(self.objects, p, self.norm))

    def oracle(self, alphas=graphs.FIVE, params: BuildParams | None = None) -> graphs.Oracle:
        return graphs.Oracle(dict(zip(alphas, together(*[lambda a=a: self.fixed(params, a) for a in alphas]))))


def portion(spark: SparkSession, sf_dir: str, name: str, part: int, params: BuildParams) -> "Case":
    """A workload at one `part`-th of its objects (by a hash of the id), for the study of size; its queries are the
    first hundred held-out rows by id, as the study fixes them."""
    key = (spark.sparkContext.applicationId, sf_dir, name, part, params)
    if key not in _cases:
        c = Case(spark, sf_dir, name, params)
        if part > 1:
            c.objects = stash(c.objects.where(F.pmod(F.xxhash64("id", F.lit(part)), F.lit(part)) == 0), name)
        first = c.queries.select("qid").distinct().orderBy("qid").limit(100)
        c.queries = stash(c.queries.join(F.broadcast(first), "qid", "left_semi"), "queries")
        _cases[key] = c
    return _cases[key]


def runs_of(method: str, c: Case, search, efs=SWEEP, queries: DataFrame | None = None, tag: str = "bands", k: int = 10) -> DataFrame:
    """method, ef, band (null: all), recall, n_dist, qps of search(queries, efs) -> hits with ef, n_dist, seconds.

    Recall and distance evaluations do not depend on the machine. qps is one over the mean seconds that a query takes
    inside its task, on one core, without reading the index; searches of one stage share the machine.
    """
    q = c.queries if queries is None else queries
    true = c.truth(k, queries, tag).where(F.col("rank") <= k).select("qid", "band", "id", F.lit(1).alias("true"))
    efs = tuple(dict.fromkeys(max(k, ef) for ef in efs))
    hits = search(q, efs).where(F.col("rank") <= k)
    per = hits.join(true, ["qid", "band", "id"], "left").groupBy("qid", "band", "ef").agg((F.count("true") / k).alias("recall"), F.first("n_dist").alias("n_dist"), F.first("seconds").alias("seconds"))
    every = q.select("qid", "band", F.explode(F.array(*map(F.lit, efs))).alias("ef")).join(per, ["qid", "band", "ef"], "left")
    total = every.rollup("ef", "band").agg(F.avg(F.coalesce("recall", F.lit(0.0))).alias("recall"), F.avg("n_dist").alias("n_dist"), F.avg("seconds").alias("seconds")).where("ef is not null")
    return total.select(F.lit(method).alias("method"), "ef", "band", F.round("recall", 4).alias("recall"), F.round("n_dist", 1).alias("n_dist"), F.round(1 / F.col("seconds"), 1).alias("qps"))


def gated(c: Case, params: BuildParams | None = None, gate: bool = True, shards: ShardParams = ShardParams(), probes="all"):
    ix = c.index(params, shards)
    return lambda q, efs: index.sweep(ix, q, efs, SearchParams(k=10, gate=gate, probes=probes))


def plain(ix: index.Index):
    return lambda q, efs: index.sweep(ix, q, efs, SearchParams(k=10))


def merged(m: graphs.Merge):
    return lambda q, efs: m.sweep(q, efs, 10)


def asked(o: graphs.Oracle):
    return lambda q, efs: o.sweep(q, efs, SearchParams(k=10))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range-gated search of all held-out queries: hits with their work and each query's recall."""
    c = case(spark, sf_dir)
    hits = stash(index.topk(c.index(), c.queries, SearchParams(k=10, ef_search=100)), "hits")
    return hits.join(metrics.recall(hits, c.truth()), ["qid", "band"]).select("qid", "band", "rank", "id", "dist", "n_dist", "recall")
