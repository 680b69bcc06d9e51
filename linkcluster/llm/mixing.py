"""Mixing sources to target weights by hierarchical budgeting.

A tree domain > language > source gets a token budget.  Going down, each node shares its
budget among its children in proportion to their weights; a child that cannot supply its
share (its tokens times ``max_epochs``) is filled, and what it lacks goes to its siblings
first.  Because a node's own share is capped by what its subtree can supply, only what all
siblings together lack reaches the node's own siblings, and so the ancestors.
A leaf with quota q and supply s reads q div s whole seeded epochs and then the prefix of
one more epoch, in the order of md5(seed:epoch:doc_id), that still fits.

The prefix needs no sort of a leaf: token sums of hash cells, and of the cells inside the one where it
ends, lead to a handful of rows that are ranked.  What is left is one row for each leaf with
the last hash taken, so each document is judged by itself, and no document is joined to another.

Defined cases: nulls in domain, language or source form the node ``(none)``; null or empty texts
have 0 tokens; rows of a leaf that repeat an id tie and are taken together; a very long text that does
not fit into what is left of its leaf's prefix ends the prefix; other columns may have any name; an
empty table gives an empty result; floor rounding leaves less than one token a node unspent.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from linkcluster.llm._frame import HOT_ROWS, cut, join_hot, packed, small, unpacked

NONE = "(none)"
TOKEN_PATTERN = r"[^\x20\x09-\x0D]+"
LEAF = ["domain", "lang", "source"]


#: Target weights of the production mix.
TARGETS = (("domain", "domain0", 50), ("domain", "domain1", 30), ("domain", "domain2", 20), ("lang", "en", 40), ("lang", "de", 20), ("lang", "fr", 20), ("lang", "es", 20))


@dataclass(frozen=True)
class MixConfig:
    #: Budget as a fraction (in thousandths) of all tokens.
    budget_permille: int = 500
    max_epochs: int = 4
    seed: int = 13
    #: Hexadecimal digits of the order hash that name a cell, and how often cells are divided again.
    cell_digits: int = 2
    levels: int = 2
    #: Target weights among siblings as (level, name, weight); nodes not named weigh ``other``.
    targets: tuple[tuple[str, str, int], ...] = TARGETS
    other: int = 10


def domain_of(source: Column) -> Column:
    """Three domains by the number in the source's name; a parameter of ``mix``."""
    number = F.regexp_extract(source, r"([0-9]+)$", 1)
    return F.when(number == "", F.lit(NONE)).otherwise(F.concat(F.lit("domain"), (number.cast("bigint") % 3).cast("string")))


def share(df: DataFrame, parent: list[str], name: str, budget: str) -> DataFrame:
    """Capped proportional shares among siblings: adds ``quota`` from ``budget``, ``cap`` and ``weight``."""
    order = W.partitionBy(*parent).orderBy("fill", name) if parent else W.partitionBy(F.lit(0)).orderBy("fill", name)
    whole = W.partitionBy(*parent) if parent else W.partitionBy(F.lit(0))
    d = df.withColumn("fill", F.col("cap").cast("double") / F.col("weight").cast("double"))
    d = d.withColumn("rank", F.row_number().over(order))
    d = d.withColumn("left", F.col(budget) - F.coalesce(F.sum("cap").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    d = d.withColumn("rest", F.sum("weight").over(order.rowsBetween(W.currentRow, W.unboundedFollowing)))
    d = d.withColumn("level", F.col("left").cast("double") / F.col("rest").cast("double"))
    d = d.withColumn("short", F.col("fill") <= F.col("level"))
    d = d.withColumn("first", F.min(F.when(~F.col("short"), F.struct("rank", "level"))).over(whole))
    filled = F.col("first").isNull() | (F.col("rank") < F.col("first.rank"))
    d = d.withColumn("quota", F.when(filled, F.col("cap")).otherwise(F.greatest(F.lit(0), F.floor(F.col("first.level") * F.col("weight").cast("double"))).cast("bigint")))
    return d.drop("fill", "rank", "left", "rest", "level", "short", "first")


def target(level: str, cfg: MixConfig) -> Column:
    """The target weight of a node of that level among its siblings."""
    out = F.lit(cfg.other)
    for at, name, weight in cfg.targets:
        if at == level:
            out = F.when(F.col(level) == name, F.lit(weight)).otherwise(out)
    return out.cast("bigint")


def leaf_quotas(leaves: DataFrame, cfg: MixConfig, weights: DataFrame | None = None) -> DataFrame:
    """(domain, lang, source, supply, quota) from (domain, lang, source, supply).

    Weights come from ``cfg.targets``.  ``weights`` (domain, lang, source, weight) overrides them leaf by leaf;
    a node's weight is then the sum of its leaves'.
    """
    total = lambda d, by: d.groupBy(*by).agg(F.sum("supply").alias("supply"), *([F.sum("weight").alias("weight")] if weights is not None else []))
    if weights is not None:
        leaves = leaves.join(weights, LEAF, "left").withColumn("weight", F.coalesce("weight", F.lit(1)))
    langs = total(leaves, LEAF[:2])
    domains = total(langs, LEAF[:1])
    if weights is None:
        leaves, langs, domains = (d.withColumn("weight", target(level, cfg)) for d, level in ((leaves, "source"), (langs, "lang"), (domains, "domain")))
    cap = F.col("supply") * cfg.max_epochs
    whole = domains.agg(F.sum("supply").alias("all"))
    top = domains.crossJoin(F.broadcast(whole)).withColumn("cap", cap).withColumn("budget", F.floor(F.col("all") * cfg.budget_permille / 1000).cast("bigint"))
    top = share(top, [], "domain", "budget").select("domain", F.col("quota").alias("budget"))
    mid = share(langs.withColumn("cap", cap).join(top, "domain"), ["domain"], "lang", "budget").select("domain", "lang", F.col("quota").alias("budget"))
    low = share(leaves.withColumn("cap", cap).join(mid, ["domain", "lang"]), ["domain", "lang"], "source", "budget")
    return low.select(*LEAF, "supply", "quota")


def _leaf_of(source: Column, lang: Column, domain) -> dict[str, Column]:
    return {"domain": F.coalesce(domain(source), F.lit(NONE)), "lang": F.coalesce(lang, F.lit(NONE)), "source": F.coalesce(source, F.lit(NONE))}


def _order(cfg: MixConfig) -> Column:
    """The seeded hash that orders a leaf's documents in the epoch of which a prefix is read."""
    return F.md5(F.concat_ws(":", F.lit(str(cfg.seed)), F.col("whole").cast("string"), F.coalesce(F.col("id").cast("string"), F.lit(""))).cast("binary"))


def _planned(docs: DataFrame, cfg: MixConfig, domain, weights: DataFrame | None, key: str) -> tuple[DataFrame, DataFrame]:
    """(id, leaf, tokens) of every row, and for each leaf (quota, whole, part, ended, upto): ``upto`` is the last hash taken."""
    tokens = F.coalesce(F.regexp_count("text", F.lit(TOKEN_PATTERN)), F.lit(0)).cast("bigint")
    slim = cut(docs.select(F.col(key).alias("id"), *[c.alias(n) for n, c in _leaf_of(F.col("source"), F.col("lang"), domain).items()], tokens.alias("tokens")))
    leaves = cut(slim.groupBy(*LEAF).agg(F.sum("tokens").alias("supply"), F.count(F.lit(1)).alias("rows")))
    plan = leaf_quotas(leaves.drop("rows"), cfg, weights).join(leaves.select(*LEAF, "rows"), LEAF)
    plan = plan.withColumn("whole", F.when(F.col("supply") > 0, F.floor(F.col("quota") / F.greatest("supply", F.lit(1)))).otherwise(0).cast("bigint"))
    plan = cut(plan.withColumn("part", F.col("quota") - F.col("whole") * F.col("supply")))
    rows = join_hot(slim, plan.where("part > 0"), LEAF, F.col("rows") > HOT_ROWS, "id").withColumn("order", _order(cfg)).select(*LEAF, "part", "tokens", "order")
    ends = plan.where("part > 0").select(*LEAF, F.lit("").alias("cell"), F.lit(0).cast("bigint").alias("before"))
    for level in range(cfg.levels):
        inside = rows.withColumn("cell", F.substring("order", 1, cfg.cell_digits * level)).join(small(ends), [*LEAF, "cell"]) if level else rows.withColumn("before", F.lit(0).cast("bigint"))
        cells = inside.groupBy(*LEAF, "part", "before", F.substring("order", 1, cfg.cell_digits * (level + 1)).alias("cell")).agg(F.sum("tokens").alias("held"))
        so_far = F.col("before") + F.sum("held").over(W.partitionBy(*LEAF).orderBy("cell").rowsBetween(W.unboundedPreceding, W.currentRow))
        over = cells.withColumn("total", so_far).where("total > part").groupBy(*LEAF).agg(F.min(F.struct("cell", (F.col("total") - F.col("held")).alias("before"))).alias("end"))
        ends = cut(over.select(*LEAF, F.col("end.cell").alias("cell"), F.col("end.before").alias("before")))
    # the rows of the last cell alone are ranked; ties in hash fall together
    edge = rows.withColumn("cell", F.substring("order", 1, cfg.cell_digits * cfg.levels)).join(small(ends), [*LEAF, "cell"])
    edge = edge.withColumn("total", F.col("before") + F.sum("tokens").over(W.partitionBy(*LEAF).orderBy("order").rangeBetween(W.unboundedPreceding, W.currentRow)))
    last = edge.where("total <= part").groupBy(*LEAF).agg(F.max("order").alias("taken"))
    ends = ends.join(last, LEAF, "left").select(*LEAF, F.lit(True).alias("ended"), F.coalesce("taken", "cell").alias("upto"))
    return slim, cut(plan.join(ends, LEAF, "left"))


def _copies(cfg: MixConfig) -> Column:
    """How often a row is read.  A cell's name sorts before all hashes in it, so it stands for "none of this cell"."""
    taken = (F.col("part") > 0) & (F.col("ended").isNull() | (_order(cfg) <= F.col("upto")))
    return F.col("whole") + taken.cast("bigint")


def choose(docs: DataFrame, cfg: MixConfig = MixConfig(), domain=domain_of, weights: DataFrame | None = None, key: str = "doc_id") -> DataFrame:
    """(key, domain, lang, source, tokens, quota, copies) of every document; ``copies`` is how often it is read."""
    slim, plan = _planned(docs, cfg, domain, weights, key)
    rows = join_hot(slim, plan, LEAF, F.col("rows") > HOT_ROWS, "id")
    return rows.select(F.col("id").alias(key), *LEAF, "tokens", "quota", _copies(cfg).alias("copies"))


def mix_documents(docs: DataFrame, cfg: MixConfig = MixConfig(), domain=domain_of, weights: DataFrame | None = None, key: str = "doc_id") -> DataFrame:
    """The documents read, with all their columns, each as often as its leaf's epochs say."""
    _, plan = _planned(docs, cfg, domain, weights, key)
    rows = packed(docs, id=F.col(key), **_leaf_of(F.col("source"), F.col("lang"), domain))
    rows = join_hot(rows, plan, LEAF, F.col("rows") > HOT_ROWS, "id").withColumn("copies", _copies(cfg)).where("copies > 0")
    return unpacked(rows.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("bigint"), "copies"))), docs)
