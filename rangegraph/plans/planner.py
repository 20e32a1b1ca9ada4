"""Plans for a filtered search. The caller says whether the answer must be exact; sizes only decide between plans of that guarantee."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import exact, index
from ..operators.index import Index
from ..schema import Norm, SearchParams
from ..storage import stash

FEW = 0.05  # a filter that keeps less than this share leaves too few of a graph's nodes to walk on


@dataclass(frozen=True)
class Choice:
    method: str
    why: str


def choose(objects: int, kept: int, guarantee: str) -> Choice:
    """How to search `kept` of `objects` rows. 'exact': a scan. 'approximate': the graph; what its walk can't give is scanned."""
    if guarantee not in ("exact", "approximate"):
        raise ValueError("guarantee is 'exact' or 'approximate'")
    if guarantee == "exact":
        return Choice("scan", "exact")
    if kept < FEW * objects:
        return Choice("scan", "the filter keeps few objects")
    return Choice("graph", "filter after the search" if kept < objects else "all objects")


def topk(objects: DataFrame, queries: DataFrame, norm: Norm, k: int = 10, condition=None, ix: Index | None = None, ef: int = 100, guarantee: str = "exact") -> tuple[DataFrame, Choice]:
    """Top-k of the objects that meet a condition. A graph search asks for more and filters; what then lacks is scanned."""
    kept = objects.where(condition) if condition is not None else objects
    n, m = objects.count(), kept.count()
    choice = choose(n, m, guarantee)
    if choice.method == "scan":
        return exact.topk(kept, queries, norm, k), choice
    if ix is None:
        raise ValueError("an approximate search needs an index")
    wide = min(4 * k * max(1, n // max(m, 1)), 10 * ef) if condition is not None else k
    hits = index.topk(ix, queries, SearchParams(wide, max(ef, wide)))
    if condition is not None:
        hits = hits.join(kept.select("id"), "id", "left_semi")
    best = stash(exact.final_topk(hits.select("qid", "band", "id", "dist"), k), "hits")
    short = queries.join(best.groupBy("qid", "band").count().where(F.col("count") >= min(k, m)), ["qid", "band"], "left_anti")
    return best.join(short.select("qid", "band"), ["qid", "band"], "left_anti").unionByName(exact.topk(kept, short, norm, k)), choice
