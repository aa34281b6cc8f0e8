"""Mixing of sources to target weights by hierarchical budgets over a tree of levels (domain, language, source).

A total budget of tokens flows down the tree: a node's budget is shared among its children by their weights. A child
takes no more than it can hold (MAX_EPOCHS times the tokens of the leaves below it that positive weights reach); what it cannot take goes to its siblings by weight,
and only what all of them cannot take was never given to their parent, so it went to the parent's siblings. Each sharing is
solved at once by sorting the siblings by capacity over weight, as window sums.

A leaf passes over its documents in epochs, each in an order of its own: by the MD5 of seed, epoch and doc_id. Whole
epochs take every document; the last one takes the longest prefix within what is left. The prefix is found from
sums over ranges of the hash, then within the one range where the budget ends, so a leaf with a third of all rows
meets in no single task. It is kept as one cut per leaf: a document is taken if its hash is not over its leaf's cut.

Weights are given per name, or else a power of a node's tokens. Tokens are words parted by ASCII white space.

Cases: null text has no tokens; documents without tokens are never taken, nor those a weight of zero or less lies above; null level values form the leaf ``none``; rows of equal
doc_id go together; an empty table gives an empty table; other columns are ignored by ``mix_documents`` and passed through by ``draw``.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens.llm.common import Scratch

#: Leaves up to which the cuts are sent to every task (some 100 bytes each); beyond, they are joined by shuffle.
BROADCAST_LEAVES = 100_000
#: Hexadecimal digits of the hash ranges, coarse to fine: each finer sum is taken within the one range of a leaf where its budget ends,
#: so a leaf has 256 rows in the first and at most 4096 in the second, whatever it holds.
RANGE_DIGITS = (2, 5)
_WORD = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class Level:
    """A level of the tree: its column, weights by name (others get ``rest``), or tokens to a power where there are none."""

    name: str
    value: Column
    weights: dict[str, float] = field(default_factory=dict)
    rest: float = 0.0
    power: float = 0.5


@dataclass(frozen=True)
class MixPlan:
    levels: tuple[Level, ...]
    share: float = 0.6
    max_epochs: int = 2
    seed: int = 17


def default_plan() -> MixPlan:
    """Four domains of five sources each, languages and sources by the root of their tokens."""
    number = F.regexp_extract("source", r"(\d+)", 1).cast("int")
    domain = F.concat(F.lit("domain"), F.coalesce(F.floor(number / 5).cast("string"), F.lit("none")))
    return MixPlan((Level("domain", domain, {"domain0": 0.4, "domain1": 0.3, "domain2": 0.2, "domain3": 0.1}, 0.1), Level("lang", F.col("lang")), Level("source", F.col("source"))))


def _named(plan: MixPlan) -> list[Column]:
    return [F.coalesce(level.value, F.lit("none")).alias(f"__{level.name}") for level in plan.levels]


def _keys(plan: MixPlan) -> list[str]:
    return [f"__{level.name}" for level in plan.levels]


def _order_key(plan: MixPlan, epoch: Column) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(plan.seed)), epoch.cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary"))


def budgets(leaves: DataFrame, plan: MixPlan) -> DataFrame:
    """From (keys, supply) of each leaf: (keys, supply, budget)."""
    keys = _keys(plan)
    total = leaves.agg(F.sum("supply")).first()[0] or 0
    given = {k: F.greatest(F.coalesce(F.element_at(F.create_map(*(F.lit(x) for kv in level.weights.items() for x in kv)), F.col(k)), F.lit(level.rest)), F.lit(0.0)) for k, level in zip(keys, plan.levels, strict=True) if level.weights}
    reached = reduce(and_, (w > 0 for w in given.values()), F.lit(True))
    leaves = leaves.withColumn("__room", F.when(reached, F.col("supply").cast("double") * plan.max_epochs).otherwise(F.lit(0.0)))
    upper = leaves.sparkSession.createDataFrame([(float(total) * plan.share,)], "budget double")
    for i, level in enumerate(plan.levels):
        at, above = keys[: i + 1], keys[:i]
        nodes = leaves.groupBy(*at).agg(F.sum("supply").alias("supply"), F.sum("__room").alias("room"))
        nodes = nodes.withColumn("weight", given[at[-1]] if at[-1] in given else F.pow(F.col("supply").cast("double"), F.lit(level.power)))
        nodes = nodes.join(upper.drop("supply"), above) if above else nodes.crossJoin(F.broadcast(upper))
        by = W.partitionBy(*above)
        order = by.orderBy(F.when(F.col("weight") > 0, F.col("room") / F.col("weight")).otherwise(F.lit(float("inf"))), at[-1])
        nodes = nodes.select(
            "*", F.row_number().over(order).alias("rank"),
            F.coalesce(F.sum("room").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)).alias("taken"),
            F.sum("weight").over(order.rowsBetween(0, W.unboundedFollowing)).alias("open"),
        )
        nodes = nodes.withColumn("rate", F.when(F.col("open") > 0, (F.col("budget") - F.col("taken")) / F.col("open")).otherwise(F.lit(0.0)))
        nodes = nodes.withColumn("full", F.col("room") <= F.col("rate") * F.col("weight"))
        level_rate = F.min(F.when(~F.col("full"), F.struct("rank", "rate"))).over(by)
        upper = nodes.select(*at, "supply", F.when(F.col("full"), F.col("room")).otherwise(level_rate["rate"] * F.col("weight")).alias("budget"))
    return upper.select(*keys, "supply", F.floor(F.col("budget") + 1e-6).cast("bigint").alias("budget"))


def counted(docs: DataFrame, plan: MixPlan) -> DataFrame:
    """(doc_id, keys, tokens) of every document."""
    return docs.select("doc_id", *_named(plan), F.coalesce(F.size(F.regexp_extract_all("text", F.lit(_WORD), F.lit(0))), F.lit(0)).cast("bigint").alias("tokens"))


def leaf_cuts(rows: DataFrame, plan: MixPlan) -> DataFrame:
    """(keys, supply, budget, epochs, cut) of each leaf with tokens, from ``counted`` rows. The leaves and their budgets are written, as every later step reads them again."""
    keys, scratch = _keys(plan), Scratch(rows.sparkSession)
    live = rows.where("tokens > 0")
    got = scratch.table(budgets(scratch.table(live.groupBy(*keys).agg(F.sum("tokens").alias("supply"))), plan))
    got = got.select("*", F.floor(F.col("budget") / F.col("supply")).cast("bigint").alias("epochs")).withColumn("left", F.col("budget") - F.col("epochs") * F.col("supply"))
    placed = live.join(F.broadcast(got.select(*keys, "epochs", "left")), keys) if got.count() <= BROADCAST_LEAVES else live.join(got.select(*keys, "epochs", "left"), keys)
    inside = placed.select(*keys, "left", "tokens", _order_key(plan, F.col("epochs")).alias("at"), F.lit(0).cast("bigint").alias("before"))
    ends = None
    for digits in RANGE_DIGITS:
        inside = inside.withColumn("range", F.substring("at", 1, digits))
        sums = inside.groupBy(*keys, "left", "before", "range").agg(F.sum("tokens").alias("n"))
        sums = sums.withColumn("upto", F.col("before") + F.sum("n").over(W.partitionBy(*keys).orderBy("range")))
        ends = sums.where(F.col("upto") > F.col("left")).groupBy(*keys).agg(F.min("range").alias("range"), F.min_by(F.col("upto") - F.col("n"), "range").alias("before"))
        inside = inside.drop("before").join(ends, [*keys, "range"])
    sums = inside.withColumn("cum", F.col("before") + F.sum("tokens").over(W.partitionBy(*keys, "range").orderBy("at")))
    last = sums.where(F.col("cum") <= F.col("left")).groupBy(*keys).agg(F.max("at").alias("last"))
    return got.join(ends.select(*keys, "range"), keys, "left").join(last, keys, "left").select(*keys, "supply", "budget", "epochs", F.coalesce("last", "range", F.lit("g")).alias("cut"))


def _copies(plan: MixPlan) -> Column:
    more = F.when(_order_key(plan, F.col("epochs")) <= F.col("cut"), 1).otherwise(0)
    return F.when(F.coalesce(F.col("tokens"), F.lit(0)) > 0, F.coalesce(F.col("epochs") + more, F.lit(0))).otherwise(0).cast("bigint")


def _attached(rows: DataFrame, cuts: DataFrame, plan: MixPlan) -> DataFrame:
    small = cuts.select(*_keys(plan), "epochs", "cut")
    return rows.join(F.broadcast(small) if small.count() <= BROADCAST_LEAVES else small, _keys(plan), "left")


def mix_documents(docs: DataFrame, plan: MixPlan | None = None) -> DataFrame:
    """(doc_id, level values, n_tokens, copies): how many times each document is taken."""
    plan = plan or default_plan()
    scratch = Scratch(docs.sparkSession)
    rows = scratch.table(counted(docs, plan))
    cuts = scratch.table(leaf_cuts(rows, plan))
    return _attached(rows, cuts, plan).select("doc_id", *(F.col(k).alias(k[2:]) for k in _keys(plan)), F.col("tokens").alias("n_tokens"), _copies(plan).alias("copies"))


def draw(docs: DataFrame, plan: MixPlan | None = None) -> DataFrame:
    """The rows of the mix, each as often as it is taken, with the input's columns as they were. Texts are not shuffled while the
    leaves are few enough to send around."""
    plan = plan or default_plan()
    scratch = Scratch(docs.sparkSession, tidy=True)
    cuts = scratch.table(leaf_cuts(scratch.table(counted(docs, plan)), plan))
    rows = docs.select("*", *_named(plan), F.when(F.trim(F.translate(F.coalesce("text", F.lit("")), "\t\n\x0b\f\r", "     ")) != "", 1).otherwise(0).alias("tokens"))
    times = _attached(rows, cuts, plan).withColumn("__times", _copies(plan)).where("__times > 0")
    return times.withColumn("__one", F.explode(F.sequence(F.lit(1), F.col("__times")))).select(*docs.columns)


#: ``mix_documents`` with the default plan over ``documents``, for DuckDB.
SQL = r"""
WITH d AS (
  SELECT doc_id, 'domain' || coalesce(CAST(TRY_CAST(nullif(regexp_extract(source, '(\d+)', 1), '') AS INT) // 5 AS VARCHAR), 'none') AS domain,
    coalesce(lang, 'none') AS lang, coalesce(source, 'none') AS source, CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS tokens
  FROM documents),
leaf AS (SELECT domain, lang, source, CAST(sum(tokens) AS BIGINT) AS supply FROM d WHERE tokens > 0 GROUP BY ALL),
n1 AS (SELECT domain, sum(supply) AS supply, CASE domain WHEN 'domain0' THEN 0.4 WHEN 'domain1' THEN 0.3 WHEN 'domain2' THEN 0.2 ELSE 0.1 END::DOUBLE AS weight,
  CAST(sum(supply) AS DOUBLE) * 2 AS room, (SELECT CAST(sum(supply) AS DOUBLE) * 0.6 FROM leaf) AS budget FROM leaf GROUP BY ALL),
r1 AS (SELECT *, row_number() OVER o AS rank, (budget - coalesce(sum(room) OVER (ORDER BY room / weight, domain ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
  / sum(weight) OVER (ORDER BY room / weight, domain ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rate FROM n1 WINDOW o AS (ORDER BY room / weight, domain)),
b1 AS (SELECT domain, CASE WHEN room <= rate * weight THEN room ELSE (SELECT arg_min(rate, rank) FROM r1 x WHERE x.room > x.rate * x.weight) * weight END AS budget FROM r1),
n2 AS (SELECT domain, lang, sqrt(CAST(sum(supply) AS DOUBLE)) AS weight, CAST(sum(supply) AS DOUBLE) * 2 AS room, any_value(budget) AS budget FROM leaf JOIN b1 USING (domain) GROUP BY ALL),
r2 AS (SELECT *, row_number() OVER (PARTITION BY domain ORDER BY room / weight, lang) AS rank,
  (budget - coalesce(sum(room) OVER (PARTITION BY domain ORDER BY room / weight, lang ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
  / sum(weight) OVER (PARTITION BY domain ORDER BY room / weight, lang ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rate FROM n2),
l2 AS (SELECT domain, arg_min(rate, rank) AS level_rate FROM r2 WHERE room > rate * weight GROUP BY domain),
b2 AS (SELECT domain, lang, CASE WHEN room <= rate * weight THEN room ELSE level_rate * weight END AS budget FROM r2 LEFT JOIN l2 USING (domain)),
n3 AS (SELECT domain, lang, source, supply, sqrt(CAST(supply AS DOUBLE)) AS weight, CAST(supply AS DOUBLE) * 2 AS room, budget FROM leaf JOIN b2 USING (domain, lang)),
r3 AS (SELECT *, row_number() OVER (PARTITION BY domain, lang ORDER BY room / weight, source) AS rank,
  (budget - coalesce(sum(room) OVER (PARTITION BY domain, lang ORDER BY room / weight, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
  / sum(weight) OVER (PARTITION BY domain, lang ORDER BY room / weight, source ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rate FROM n3),
l3 AS (SELECT domain, lang, arg_min(rate, rank) AS level_rate FROM r3 WHERE room > rate * weight GROUP BY ALL),
b3 AS (SELECT domain, lang, source, supply, CAST(floor(CASE WHEN room <= rate * weight THEN room ELSE level_rate * weight END + 1e-6) AS BIGINT) AS budget FROM r3 LEFT JOIN l3 USING (domain, lang)),
e AS (SELECT *, budget // supply AS epochs, budget % supply AS rest FROM b3),
k AS (SELECT d.*, e.epochs, e.rest, md5('17:' || CAST(e.epochs AS VARCHAR) || ':' || coalesce(CAST(doc_id AS VARCHAR), '')) AS spot FROM d LEFT JOIN e USING (domain, lang, source)),
c AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY spot) AS upto FROM k)
SELECT doc_id, domain, lang, source, tokens AS n_tokens, CAST(CASE WHEN tokens > 0 THEN epochs + CASE WHEN upto <= rest THEN 1 ELSE 0 END ELSE 0 END AS BIGINT) AS copies FROM c
"""
