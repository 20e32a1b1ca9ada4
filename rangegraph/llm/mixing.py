"""Mixing sources to target weights by budgets on a tree of domain, language and source.

A token budget is handed down the tree: at each node the children get their shares by weight, none more
than its subtree can give; what a child can't use goes to its siblings by their weights, and only what
a whole family can't use stays with the node above, which hands it to its own siblings. With the capacity
of each subtree known from below, that is one water level per family: a window over the children in the
order of capacity by weight.

A leaf's documents are read in seeded epochs: each epoch is the leaf in the order of a hash of seed, epoch
and doc_id. The leaf takes whole epochs and then the prefix of the next one whose tokens fit its budget.
The prefix is found by sums over 4,096 ranges of the hash; only the range where the budget ends is ordered
by row, so no task sees a whole source, however large.

Defined cases: null text has 0 tokens; null lang and source form leaves of their own; unknown domains,
languages and sources have weight 1; documents without tokens belong to the epochs of their leaf; rows
that repeat a doc_id are drawn alike (the order among equal rows has no effect on the result); weights
of 0 give nothing; an empty table gives an empty result; further columns of documents are kept by `mix`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh, stash

#: source (its number modulo the list) -> domain, as the tables name sources src0, src1, ...
DOMAINS = ("web", "books", "code", "forum")
DOMAIN_WEIGHTS = {"web": 0.4, "books": 0.3, "code": 0.2, "forum": 0.1}
LANGUAGE_WEIGHTS = {"en": 0.5, "de": 0.2, "fr": 0.2, "es": 0.1}
BUDGET_SHARE = 0.8
EPOCHS = 2
SEED = 7
DIGITS = 3


def domain_of(source: Column) -> Column:
    number = F.regexp_extract(F.coalesce(source, F.lit("")), "([0-9]+)$", 1)
    named = F.element_at(F.array(*map(F.lit, DOMAINS)), (F.pmod(F.substring(number, -9, 9).cast("int"), F.lit(len(DOMAINS))) + 1).cast("int"))
    return F.when(number == "", F.lit("other")).otherwise(named)


def token_count(text: Column) -> Column:
    """Words cut at ASCII white space."""
    spaced = F.regexp_replace(F.coalesce(text, F.lit("")), "[ \\t\\n\\r\\f\\u000B]+", " ")
    trimmed = F.trim(spaced)
    return F.when(trimmed == "", F.lit(0)).otherwise(F.char_length(trimmed) - F.char_length(F.replace(trimmed, F.lit(" "), F.lit(""))) + 1).cast("long")


def weight_of(column: str, weights: dict[str, float]) -> Column:
    out = F.lit(1.0)
    for k, v in weights.items():
        out = F.when(F.col(column) == k, F.lit(float(v))).otherwise(out)
    return out


def water_level(children: DataFrame, parent: list[str], order: list[str]) -> DataFrame:
    """Adds `budget` to children (weight, capacity) of families with `parent_budget`."""
    family = Window.partitionBy(*parent) if parent else Window.partitionBy(F.lit(0))
    ratio = F.when(F.col("weight") > 0, F.col("capacity") / F.col("weight")).otherwise(F.lit(float("inf")))
    w = family.orderBy(ratio, *order)
    before = w.rowsBetween(Window.unboundedPreceding, -1)
    after = w.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    level = (F.col("parent_budget") - F.coalesce(F.sum(F.when(F.col("weight") > 0, F.col("capacity")).otherwise(0.0)).over(before), F.lit(0.0))) / F.nullif(F.sum("weight").over(after), F.lit(0.0))
    marked = children.withColumn("ratio", ratio).withColumn("level", level).withColumn("full", F.coalesce(F.col("ratio") <= F.col("level"), F.lit(False)))
    # the level of the first child that is not full holds for all behind it
    first = F.first(F.when(~F.col("full"), F.col("level")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return marked.withColumn("budget", F.when(F.col("weight") <= 0, 0.0).when(F.col("full"), F.col("capacity")).otherwise(F.col("weight") * first)).drop("ratio", "level", "full")


def leaf_budgets(leaves: DataFrame, share: float, epochs: int, domains: dict[str, float], languages: dict[str, float], sources: dict[str, float]) -> DataFrame:
    """domain, lang, source, tokens, budget (whole tokens) from the leaves' token sums."""
    top = leaves.agg(F.sum("tokens").alias("all_tokens"))
    leaf = leaves.withColumn("weight", weight_of("source", sources)).withColumn("capacity", F.when(F.col("weight") > 0, F.col("tokens") * float(epochs)).otherwise(0.0))
    lang = leaf.groupBy("domain", "lang").agg(F.sum("capacity").alias("capacity")).withColumn("weight", weight_of("lang", languages)).withColumn("capacity", F.when(F.col("weight") > 0, F.col("capacity")).otherwise(0.0))
    dom = lang.groupBy("domain").agg(F.sum("capacity").alias("capacity")).withColumn("weight", weight_of("domain", domains)).withColumn("capacity", F.when(F.col("weight") > 0, F.col("capacity")).otherwise(0.0))
    at_dom = water_level(dom.crossJoin(F.broadcast(top)).withColumn("parent_budget", F.col("all_tokens") * share), [], ["domain"])
    at_lang = water_level(lang.join(at_dom.select("domain", F.col("budget").alias("parent_budget")), "domain"), ["domain"], ["lang"])
    upper = at_lang.select("domain", F.col("lang").alias("l"), F.col("budget").alias("parent_budget"))
    at_leaf = water_level(leaf.join(upper, (leaf.domain == upper.domain) & leaf.lang.eqNullSafe(upper.l)).drop(upper.domain).drop("l"), ["domain", "lang"], ["source"])
    return at_leaf.select("domain", "lang", "source", "tokens", F.floor(F.col("budget") + 1e-6).cast("long").alias("budget"))


def draw(docs: DataFrame, share: float = BUDGET_SHARE, epochs: int = EPOCHS, seed: int = SEED, domains=DOMAIN_WEIGHTS, languages=LANGUAGE_WEIGHTS, sources=None) -> DataFrame:
    """doc_id, domain, lang, source, n_tokens, epoch: a row for each time that a document is taken."""
    leaf = ["domain", "lang", "source"]
    base = stash(docs.select("doc_id", domain_of(F.col("source")).alias("domain"), "lang", "source", token_count(F.col("text")).alias("n_tokens")), "leaves")
    sums = base.groupBy(*leaf).agg(F.sum("n_tokens").alias("tokens"))
    budgets = leaf_budgets(sums, share, epochs, domains, languages, sources or {})
    full = F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(F.lit(0)).cast("int")
    plan = stash(budgets.withColumn("whole", F.least(full, F.lit(epochs))).withColumn("rest", F.when(F.col("whole") < epochs, F.col("budget") - F.col("whole") * F.col("tokens")).otherwise(F.lit(0))), "budgets")
    p = plan.select(*[F.col(c).alias("_" + c) for c in leaf], "whole", "rest")
    same = (base.domain == p["_domain"]) & base.lang.eqNullSafe(p["_lang"]) & base.source.eqNullSafe(p["_source"])
    # the table of leaves is as large as the tree of names, not as the corpus; AQE may still choose to sort
    rows = base.join(p, same).drop("_domain", "_lang", "_source")
    taken = rows.where("whole > 0").select("doc_id", *leaf, "n_tokens", F.explode(F.sequence(F.lit(0), F.col("whole") - 1)).alias("epoch"))
    key = F.md5(F.concat_ws(":", F.lit(seed).cast("string"), F.col("whole").cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    part = rows.where("rest > 0").withColumn("key", key).withColumn("range", F.substring("key", 1, DIGITS))
    ranges = part.groupBy(*leaf, "range").agg(F.sum("n_tokens").alias("in_range"), F.first("rest").alias("limit"))
    w = Window.partitionBy(*leaf).orderBy("range")
    ranges = ranges.withColumn("upto", F.sum("in_range").over(w.rowsBetween(Window.unboundedPreceding, 0))).withColumn("before", F.col("upto") - F.col("in_range"))
    r = ranges.where("before < limit or upto <= limit").select(*[F.col(c).alias("_" + c) for c in leaf], F.col("range").alias("_range"), "before", "upto")
    on = (part.domain == r["_domain"]) & part.lang.eqNullSafe(r["_lang"]) & part.source.eqNullSafe(r["_source"]) & (part.range == r["_range"])
    inside = part.join(r, on).drop("_domain", "_lang", "_source", "_range")
    columns = ["doc_id", *leaf, "n_tokens", F.col("whole").alias("epoch")]
    sure = inside.where("upto <= rest").select(*columns)
    edge = Window.partitionBy(*leaf, "range").orderBy("key", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, 0)
    last = inside.where("upto > rest").withColumn("sum", F.col("before") + F.sum("n_tokens").over(edge)).where("sum <= rest").select(*columns)
    return taken.unionByName(sure).unionByName(last)


def mix(docs: DataFrame, **options) -> DataFrame:
    """The documents as often as they are drawn, with all their columns.

    Rows that share doc_id, lang and source share their draws: each gets as many, and those with the fewest tokens one
    more while some are left, as the last epoch takes them. So no leaf gets more than its budget.
    """
    names = ("doc_id", "lang", "source")
    key = [fresh(docs.columns, x) for x in ("k", "l", "s")]
    times, rows, place, each = (fresh(docs.columns, x) for x in ("times", "rows", "place", "each"))
    drawn = draw(docs, **options).groupBy(*names).agg(F.count(F.lit(1)).cast("int").alias(times)).select(*[F.col(n).alias(k) for n, k in zip(names, key)], times)
    w = Window.partitionBy(*names)
    counted = docs.withColumn(rows, F.count(F.lit(1)).over(w))
    order = F.when(F.col(rows) > 1, token_count(F.col("text"))), F.when(F.col(rows) > 1, F.xxhash64("text"))
    placed = counted.withColumn(place, F.row_number().over(w.orderBy(*order)))
    on = [F.col(n).eqNullSafe(F.col(k)) for n, k in zip(names, key)]
    n = F.floor(F.col(times) / F.col(rows)) + F.when(F.col(place) <= F.pmod(F.col(times), F.col(rows)), 1).otherwise(0)
    out = placed.join(drawn, on[0] & on[1] & on[2]).withColumn(each, n.cast("int")).where(F.col(each) > 0)
    return out.withColumn(each, F.explode(F.sequence(F.lit(1), F.col(each)))).select(*[F.col(f"`{c}`") for c in docs.columns])
