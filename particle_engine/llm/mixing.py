"""Mixing sources to target weights by hierarchical budgeting, in DataFrame functions only.

The tree is domain, language, source.  A node's budget goes to its children by
weight; a child that holds less than its share takes what it has and its
shortage is spread over its siblings by weight (water filling).  What a child can
hold is the sum below it, so a shortage climbs to the parent's siblings only
once all siblings are full.  A leaf spends its budget on whole epochs first and
then on a prefix of the next epoch, whose order is a seeded hash of that epoch
and the document.  The prefix is found in two steps (sums per hash bucket, then
rows of the one bucket where the budget ends), so no leaf is ordered in one task.

Defined results: null language or source is the leaf named ''; null or empty
texts have no tokens and are taken with whole epochs, or in a prefix that
reaches them; a row is identified by doc_id, rows that repeat it count each;
budgets are integers and rounding leaves less than a token per child unspent.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from particle_engine.llm.common import bounded_broadcast, stage_table

WORD = r"[^\x20\x09-\x0D]+"
LEAF = ["domain", "lang", "source"]
#: Production weights of the tree's levels; sources weigh alike.
DOMAIN_WEIGHTS = {"web": 5, "reference": 3, "social": 2}
LANG_WEIGHTS = {"en": 4, "de": 2, "fr": 2}
OTHER_WEIGHT = 1
BUDGET_PERCENT, MAX_EPOCHS, SEED = 80, 2, 17


def domain_of(source: Column) -> Column:
    """Domain by the number a source's name ends with: 0-9 web, 10-14 reference, others social; no number: other."""
    number = F.regexp_extract(source, "([0-9]{1,9})$", 1)
    n = F.when(number != "", number.cast("int"))
    return F.when(n.isNull(), "other").when(n < 10, "web").when(n < 15, "reference").otherwise("social")


def _weight(name: Column, weights: dict[str, int]) -> Column:
    out = F.lit(OTHER_WEIGHT)
    for key, w in weights.items():
        out = F.when(name == key, w).otherwise(out)
    return out.cast("long")


def water_fill(children: DataFrame, parent: list[str], name: str, weight: str = "w") -> DataFrame:
    """Adds ``got``: the share of ``budget`` (constant within a parent) that each child with capacity ``cap`` takes."""
    order = Window.partitionBy(*parent).orderBy(F.col("cap").cast("double") / F.col(weight), name)
    whole = Window.partitionBy(*parent)
    before = F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rest = F.sum(weight).over(order.rowsBetween(0, Window.unboundedFollowing))
    out = children.withColumn("full", F.col("cap") * rest <= (F.col("budget") - before) * F.col(weight))
    left = F.col("budget") - F.coalesce(F.sum(F.when(F.col("full"), F.col("cap"))).over(whole), F.lit(0))
    open_weight = F.sum(F.when(~F.col("full"), F.col(weight))).over(whole)
    out = out.withColumn("left", left).withColumn("open_weight", open_weight)
    return out.withColumn("got", F.when(F.col("full"), F.col("cap")).otherwise(F.expr(f"(left * {weight}) div open_weight"))).drop("full", "left", "open_weight", "budget")


def leaf_budgets(leaves: DataFrame, budget_percent: int = BUDGET_PERCENT, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """(domain, lang, source, tokens, got) from leaf token counts; the budget is a share of all tokens."""
    leaves = leaves.withColumn("cap", F.col("tokens") * max_epochs)
    total = leaves.agg(F.expr(f"coalesce(sum(tokens), 0) * {budget_percent} div 100").alias("budget"))
    domains = leaves.groupBy("domain").agg(F.sum("cap").alias("cap")).crossJoin(F.broadcast(total)).withColumn("w", _weight(F.col("domain"), DOMAIN_WEIGHTS))
    domains = water_fill(domains.withColumn("root", F.lit(0)), ["root"], "domain").select("domain", F.col("got").alias("budget"))
    langs = leaves.groupBy("domain", "lang").agg(F.sum("cap").alias("cap")).join(domains, "domain").withColumn("w", _weight(F.col("lang"), LANG_WEIGHTS))
    langs = water_fill(langs, ["domain"], "lang").select("domain", "lang", F.col("got").alias("budget"))
    sources = leaves.join(langs, ["domain", "lang"]).withColumn("w", F.lit(1).cast("long"))
    return water_fill(sources, ["domain", "lang"], "source").select(*LEAF, "tokens", "got")


def mix(docs: DataFrame, budget_percent: int = BUDGET_PERCENT, max_epochs: int = MAX_EPOCHS, seed: int = SEED) -> DataFrame:
    """(doc_id, domain, lang, source, epoch, n_tokens): one row per document and epoch taken."""
    source = F.coalesce(F.col("source").cast("string"), F.lit(""))
    rows = stage_table(
        docs.select(
            F.col("doc_id").cast("long").alias("doc_id"), domain_of(source).alias("domain"), F.coalesce(F.col("lang").cast("string"), F.lit("")).alias("lang"), source.alias("source"),
            F.coalesce(F.regexp_count(F.col("text").cast("string"), F.lit(WORD)), F.lit(0)).cast("long").alias("n_tokens"),
        ),
        "slim",
    )
    plan = leaf_budgets(rows.groupBy(*LEAF).agg(F.sum("n_tokens").alias("tokens")), budget_percent, max_epochs)
    plan = stage_table(plan.select(*LEAF, F.expr("case when tokens > 0 then got div tokens else 0 end").alias("whole"), F.expr("case when tokens > 0 then got % tokens else 0 end").alias("rest")), "leaves")
    n_leaves = plan.count()
    drawn = rows.join(bounded_broadcast(plan, 200, n_leaves), LEAF)
    drawn = drawn.withColumn("h", F.md5(F.concat_ws("|", F.lit(seed), "whole", F.coalesce(F.col("doc_id").cast("string"), F.lit("")))))
    drawn = drawn.withColumn("bucket", F.substring("h", 1, 3))
    sums = drawn.groupBy(*LEAF, "rest", "bucket").agg(F.sum("n_tokens").alias("n"))
    upto = F.sum("n").over(Window.partitionBy(*LEAF).orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0))
    edge = sums.withColumn("upto", upto).where("upto > rest and upto - n <= rest and n > 0").select(*LEAF, F.col("bucket").alias("edge"), (F.col("upto") - F.col("n")).alias("before"))
    edge = stage_table(edge, "edges")
    drawn = drawn.join(bounded_broadcast(edge, 200, n_leaves), LEAF)
    out = ["doc_id", *LEAF, "epoch", "n_tokens"]
    epochs = drawn.where("whole > 0").withColumn("epoch", F.explode(F.expr("sequence(0, cast(whole as int) - 1)"))).select(*out)
    last = F.col("whole").cast("int").alias("epoch")
    part = drawn.where("rest > 0")
    inside = part.where("bucket < edge").select("doc_id", *LEAF, last, "n_tokens")
    running = F.col("before") + F.sum("n_tokens").over(Window.partitionBy(*LEAF).orderBy("h", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, 0))
    border = part.where("bucket = edge").withColumn("running", running).where("running <= rest").select("doc_id", *LEAF, last, "n_tokens")
    return epochs.unionByName(inside).unionByName(border)


def _sql_fill(rows: str, parent: str, name: str) -> str:
    part = f"PARTITION BY {parent}"
    return f"""(SELECT *, CASE WHEN filled THEN cap ELSE ((budget - coalesce(sum(cap) FILTER (filled) OVER ({part}), 0)) * w) // sum(w) FILTER (NOT filled) OVER ({part}) END AS got
      FROM (SELECT *, cap * sum(w) OVER ({part} ORDER BY cap::DOUBLE / w, {name} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)
        <= (budget - coalesce(sum(cap) OVER ({part} ORDER BY cap::DOUBLE / w, {name} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) * w AS filled FROM {rows}))"""


def oracle() -> str:
    weight = lambda col, ws: f"(CASE {col} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in ws.items()) + f" ELSE {OTHER_WEIGHT} END)"
    return rf"""WITH d AS (SELECT doc_id, coalesce(lang, '') AS lang, coalesce(source, '') AS source, len(regexp_extract_all(coalesce(text, ''), '{WORD}')) AS n_tokens, try_cast(regexp_extract(coalesce(source, ''), '([0-9]{{1,9}})$', 1) AS INT) AS no FROM documents),
    rows_ AS (SELECT *, CASE WHEN no IS NULL THEN 'other' WHEN no < 10 THEN 'web' WHEN no < 15 THEN 'reference' ELSE 'social' END AS domain FROM d),
    leaves AS (SELECT domain, lang, source, CAST(sum(n_tokens) AS BIGINT) AS tokens, CAST(sum(n_tokens) * {MAX_EPOCHS} AS BIGINT) AS cap FROM rows_ GROUP BY ALL),
    dom AS (SELECT domain, CAST(sum(cap) AS BIGINT) AS cap, 0 AS root, {weight('domain', DOMAIN_WEIGHTS)} AS w, (SELECT CAST(sum(tokens) AS BIGINT) * {BUDGET_PERCENT} // 100 FROM leaves) AS budget FROM leaves GROUP BY domain),
    dom2 AS (SELECT domain, CAST(got AS BIGINT) AS budget FROM {_sql_fill('dom', 'root', 'domain')}),
    lan AS (SELECT domain, lang, CAST(sum(cap) AS BIGINT) AS cap, any_value(budget) AS budget, {weight('lang', LANG_WEIGHTS)} AS w FROM leaves JOIN dom2 USING (domain) GROUP BY domain, lang),
    lan2 AS (SELECT domain, lang, CAST(got AS BIGINT) AS budget FROM {_sql_fill('lan', 'domain, lang'.split(',')[0], 'lang')}),
    src AS (SELECT leaves.*, budget, 1 AS w FROM leaves JOIN lan2 USING (domain, lang)),
    plan AS (SELECT domain, lang, source, CASE WHEN tokens > 0 THEN CAST(got AS BIGINT) // tokens ELSE 0 END AS whole, CASE WHEN tokens > 0 THEN CAST(got AS BIGINT) % tokens ELSE 0 END AS rest FROM {_sql_fill('src', 'domain, lang', 'source')}),
    o AS (SELECT *, sum(n_tokens) OVER (PARTITION BY domain, lang, source ORDER BY md5('{SEED}|' || whole || '|' || coalesce(CAST(doc_id AS VARCHAR), '')), doc_id, n_tokens ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running
      FROM rows_ JOIN plan USING (domain, lang, source)),
    e AS (SELECT *, unnest(range(0, whole)) AS epoch FROM o UNION ALL SELECT *, whole AS epoch FROM o WHERE rest > 0 AND running <= rest)
    SELECT doc_id, domain, lang, source, CAST(epoch AS INTEGER) AS epoch, CAST(n_tokens AS BIGINT) AS n_tokens FROM e"""
