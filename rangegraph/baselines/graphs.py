"""The compared indexes: fixed weight, per-modality merge, overlay of five weights, one graph per weight."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.alpha import overlay_tag
from ..operators import exact, index, spatial
from ..operators.index import Index
from ..schema import SCALE, BuildParams, Norm, SearchParams, ShardParams
from ..storage import stash

FIVE = (0.1, 0.3, 0.5, 0.7, 0.9)


def at_once(*makes) -> list:
    """The results of independent builds, run at the same time: each is a job with a task per shard."""
    with ThreadPoolExecutor(8) as pool:
        return list(pool.map(lambda f: f(), makes))


def fixed_alpha(objects: DataFrame, params: BuildParams, norm: Norm, alpha0: float = 0.5, shards: ShardParams = ShardParams()) -> Index:
    """A hierarchical small-world graph for one weight, searched for any."""
    return index.build_index(objects, params.but(levels=True, pruning="rng", alpha0=alpha0), norm, shards, "fixed")


@dataclass
class Merge:
    """Two single-vector indexes. by_s None: a rectangle tree over a two-dimensional s, read exactly."""

    by_e: Index
    by_s: Index | None
    objects: DataFrame
    norm: Norm

    def sides(self, queries: DataFrame, k_primes: tuple[int, ...]) -> tuple[DataFrame, DataFrame]:
        """The lists of k' objects of each modality, for each k' (column ef), with n_dist and seconds."""
        a = index.lists(self.by_e, queries.withColumn("alpha", F.lit(1.0)), k_primes)
        if self.by_s is None:
            return a, spatial.rect_lists(self.objects, queries.withColumn("alpha", F.lit(0.0)), self.norm, k_primes)
        return a, index.lists(self.by_s, queries.withColumn("alpha", F.lit(0.0)), k_primes)

    def sweep(self, queries: DataFrame, k_primes: tuple[int, ...], k: int = 10) -> DataFrame:
        """Top-k' of each modality, united and ranked again by the hybrid distance, for each k' >= k.

        The distances of candidates are computed once for all k'. seconds: of the two searches; the ranking is a join.
        """
        k_primes = tuple(max(k, x) for x in k_primes)
        key = ["qid", "band", "ef"]
        both = None
        for i, side in enumerate(self.sides(queries, k_primes)):
            one = side.select(*key, "id", "n_dist", "seconds", F.lit(i).alias("side"))
            both = one if both is None else both.unionByName(one)
        both = stash(both, "lists")
        per = both.groupBy(*key, "side").agg(F.first("n_dist").alias("n_dist"), F.first("seconds").alias("seconds"))
        work = per.groupBy(*key).agg(F.sum("n_dist").alias("n_dist"), F.sum("seconds").alias("seconds"))
        scored = exact.distances(both.select("qid", "band", "id").distinct(), self.objects, queries, self.norm)
        rows = both.select(*key, "id").distinct().join(scored, ["qid", "band", "id"])
        w = Window.partitionBy(*key).orderBy(F.round("dist", 9), "id")
        best = rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select(*key, "rank", "id", "dist")
        return best.join(work, key)

    def search(self, queries: DataFrame, k: int = 10, k_prime: int = 100) -> DataFrame:
        return self.sweep(queries, (k_prime,), k).drop("ef")


def merge(objects: DataFrame, params: BuildParams, norm: Norm, shards: ShardParams = ShardParams()) -> Merge:
    """The two indexes; a rectangle tree takes the place of the second graph where s has two dimensions."""
    width = objects.select(F.size("s").alias("n")).first()
    flat = width is not None and width.n == 2
    by_e, by_s = at_once(lambda: fixed_alpha(objects, params, norm, 1.0, shards), lambda: None if flat else fixed_alpha(objects, params, norm, 0.0, shards))
    return Merge(by_e, by_s, objects, norm)


def rerank(a: DataFrame, b: DataFrame, objects: DataFrame, queries: DataFrame, norm: Norm, k: int) -> DataFrame:
    both = a.select("qid", "band", "id").unionByName(b.select("qid", "band", "id")).dropDuplicates()
    return exact.rescore(both, objects, queries, norm, k)


def merge_exact(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10, k_prime: int = 10) -> DataFrame:
    """The same from exact lists, so that only the loss by merging remains."""
    a = exact.topk(objects, queries.withColumn("alpha", F.lit(1.0)), norm, k_prime)
    b = exact.topk(objects, queries.withColumn("alpha", F.lit(0.0)), norm, k_prime)
    return rerank(a, b, objects, queries, norm, k)


def overlay(objects: DataFrame, params: BuildParams, norm: Norm, shards: ShardParams = ShardParams()) -> Index:
    """Five hierarchical fixed-weight graphs in one: edges of every level carry the weights of the graphs they come from.

    Levels are drawn by id, so all five have the same nodes on each level and the same entry. A query uses the edges
    of the nearest weight. A tag is stored as its band of weights, so the search is a gated descent, and a weight on
    the edge of two bands belongs to the lower one.
    """
    parts = at_once(*[lambda a=a: fixed_alpha(objects, params, norm, a, shards) for a in FIVE])
    width, key = SCALE // 5, ["shard", "level", "id"]
    tagged = work = None
    for i, p in enumerate(parts):
        e = p.nodes.select(*key, F.explode("dst").alias("dst"), F.lit(i).alias("tag"))
        tagged = e if tagged is None else tagged.unionByName(e)
        w = p.nodes.select(*key, "n_dist")
        work = w if work is None else work.unionByName(w)
    tags = tagged.groupBy(*key, "dst").agg(F.array_sort(F.collect_set("tag")).alias("tags"))
    lo = F.transform("tags", lambda t: F.when(t == 0, 0).otherwise(t * width + 1).cast("short"))
    hi = F.transform("tags", lambda t: ((t + 1) * width).cast("short"))
    per = tags.withColumn("lo", lo).withColumn("hi", hi).groupBy(*key).agg(F.sort_array(F.collect_list(F.struct("dst", "lo", "hi"))).alias("a"))
    nodes = parts[0].nodes.select(*key, "seed", "e", "s").join(per, key, "left").join(work.groupBy(*key).agg(F.sum("n_dist").alias("n_dist")), key)
    a = F.coalesce("a", F.array().cast("array<struct<dst:bigint,lo:array<smallint>,hi:array<smallint>>>"))
    out = nodes.select("shard", "id", "seed", "level", "e", "s", F.transform(a, lambda x: x.dst).alias("dst"), F.transform(a, lambda x: x.lo).alias("lo"), F.transform(a, lambda x: x.hi).alias("hi"), "n_dist")
    return Index(stash(out, "overlay"), parts[0].shards, norm, params.but(levels=True, pruning="rng"), {"build_s": sum(p.metrics["build_s"] for p in parts)})


@dataclass
class Oracle:
    """A graph per weight; a query is sent to its own."""

    graphs: dict[float, Index]

    def sweep(self, queries: DataFrame, efs: tuple[int, ...], params: SearchParams = SearchParams()) -> DataFrame:
        """As index.sweep; queries at a weight without a graph are an error."""
        own = lambda a: F.abs(F.col("alpha") - a) < 1e-9
        known = F.lit(False)
        for a in self.graphs:
            known = known | own(a)
        other = queries.where(~known).select("alpha").first()
        if other is not None:
            raise ValueError(f"no graph for weight {other.alpha}")
        out = None
        for a, g in self.graphs.items():
            one = index.sweep(g, queries.where(own(a)), efs, params)
            out = one if out is None else out.unionByName(one)
        return out

    def search(self, queries: DataFrame, params: SearchParams = SearchParams()) -> DataFrame:
        return self.sweep(queries, (params.ef_search,), params).drop("ef")


def oracle(objects: DataFrame, params: BuildParams, norm: Norm, alphas=FIVE, shards: ShardParams = ShardParams()) -> Oracle:
    return Oracle(dict(zip(alphas, at_once(*[lambda a=a: fixed_alpha(objects, params, norm, a, shards) for a in alphas]))))


def tag_of(alpha: float) -> float:
    """The overlay graph that a query of this weight uses."""
    return FIVE[overlay_tag(alpha)]
