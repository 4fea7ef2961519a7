"""Mixing sources to target weights: hierarchical budgets and seeded token prefixes. DataFrame functions only.

A budget of tokens flows down a tree (domain, language, source). At every node it is shared among the children by weight; a
child that can't use its share (its tokens times the most epochs) leaves the rest to its siblings, and only what the
whole node can't use goes to the node's own siblings: each node's capacity is the sum of its leaves'. For sorted
ratios of capacity to weight the shares have a closed form, so a level is one window over the nodes, not a loop.

A leaf takes whole epochs, then a prefix of the next one: its documents in the order of a seeded digest while their
tokens fit. Prefix sums run in two steps, over bins of the digest and within a bin, so no leaf is sorted in one task.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from laneforge.session import written

TREE = ("domain", "lang", "source")
#: Production parameters of the query and of the pipeline: integer weights by level and value; others weigh 1.
WEIGHTS = {"domain": {"d0": 4, "d1": 3, "d2": 2, "d3": 1}, "lang": {"en": 5, "de": 2, "fr": 2, "es": 2}}
EPOCHS, SHARE, SEED, BIN_DIGITS = 2, 0.9, "mix-1", 4
BROADCAST_LEAVES = 100_000


def _weight(level: str, weights: dict) -> Column:
    out = F.lit(1)
    for value, w in weights.get(level, {}).items():
        out = F.when(F.col(level) == value, w).otherwise(out)
    return out.cast("long")


def leaf_budgets(leaves: DataFrame, total: int, tree=TREE, weights=WEIGHTS) -> DataFrame:
    """Leaves (tree columns, tokens, capacity) with their budget of the total, in whole tokens.

    A task orders the children of one node of the tree, a row each; documents are not among them.
    """
    capacity = leaves.agg(F.sum("capacity")).first()[0] or 0
    nodes = leaves.withColumn("budget", F.lit(min(total, capacity)).cast("long"))
    for depth, level in enumerate(tree):
        above, here = list(tree[:depth]), list(tree[: depth + 1])
        level_nodes = nodes.groupBy(*here).agg(F.sum("capacity").alias("c"), F.first("budget").alias("b")).withColumn("w", _weight(level, weights))
        order = W.partitionBy(*above).orderBy(F.col("c") / F.col("w"), level)
        before = order.rowsBetween(W.unboundedPreceding, -1)
        after = order.rowsBetween(0, W.unboundedFollowing)
        rate = (F.col("b") - F.coalesce(F.sum("c").over(before), F.lit(0))) / F.sum("w").over(after)
        level_nodes = level_nodes.withColumn("rate", rate)
        level_nodes = level_nodes.withColumn("share", F.least(F.col("c"), F.floor(F.max("rate").over(W.partitionBy(*above)) * F.col("w"))).cast("long"))
        nodes = _null_safe_join(nodes.drop("budget"), level_nodes.select(*here, F.col("share").alias("budget")), here)
    return nodes


def _null_safe_join(left: DataFrame, right: DataFrame, on: list[str], small: bool = False) -> DataFrame:
    renamed = right.select(*[F.col(c).alias(f"_{c}") for c in on], *[c for c in right.columns if c not in on])
    match = None
    for c in on:
        one = left[c].eqNullSafe(renamed[f"_{c}"])
        match = one if match is None else match & one
    return left.join(F.broadcast(renamed) if small else renamed, match).drop(*[f"_{c}" for c in on])


def select_mix(spark: SparkSession, docs: DataFrame, domain: Column, weights=WEIGHTS, epochs: int = EPOCHS, share: float = SHARE, seed: str = SEED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All columns of docs and _domain, _tokens, _budget (of the leaf), _copies (how often the document is taken).

    A document's tokens: a quarter of its bytes, rounded up, at least one. The total is `share` of all tokens. Null
    values of a tree column are a value of their own; null texts count as empty. Rows that repeat an id and text tie
    and are taken in any order. An empty table gives no rows. Columns of these names in docs give way.
    """
    own = [c for c in docs.columns if c not in ("_domain", "_tokens", "_budget", "_copies")]
    rows = docs.select(F.struct(*own).alias("doc"), domain.alias("domain"), F.col("lang"), F.col("source"), F.col(id_col).cast("string").alias("id"), F.greatest(F.lit(1), F.expr(f"(octet_length(coalesce({text_col}, '')) + 3) div 4")).cast("long").alias("tokens"))
    light = rows.select(*TREE, "id", "tokens")
    leaves = light.groupBy(*TREE).agg(F.sum("tokens").alias("tokens")).withColumn("capacity", F.col("tokens") * epochs)
    leaves = written(spark, leaves, "mix-tree")
    total = math.floor((leaves.agg(F.sum("tokens")).first()[0] or 0) * share)
    leaves = written(spark, leaf_budgets(leaves, total, weights=weights).select(*TREE, F.col("tokens").alias("leaf_tokens"), "budget"), "mix-leaves")
    small = leaves.count() <= BROADCAST_LEAVES
    key = lambda d: d.withColumn("whole", F.expr("budget div leaf_tokens")).withColumn("key", F.md5(F.concat_ws(":", F.lit(seed), F.col("whole").cast("string"), F.coalesce("id", F.lit("")), F.col("tokens").cast("string")).cast("binary"))).withColumn("bin", F.left("key", F.lit(BIN_DIGITS)))
    keyed = key(_null_safe_join(light, leaves, list(TREE), small))
    bins = keyed.groupBy(*TREE, "bin").agg(F.sum("tokens").alias("bin_tokens"))
    bins = bins.withColumn("ahead", F.coalesce(F.sum("bin_tokens").over(W.partitionBy(*TREE).orderBy("bin").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    placed = keyed.groupBy(*TREE, "bin", "key", "id", "tokens").agg(F.count("*").alias("same"), F.first("budget").alias("budget"), F.first("leaf_tokens").alias("leaf_tokens"))
    placed = _null_safe_join(placed, bins.select(*TREE, "bin", "ahead"), [*TREE, "bin"])
    up_to = F.col("ahead") + F.sum(F.col("tokens") * F.col("same")).over(W.partitionBy(*TREE, "bin").orderBy("key", "id", "tokens").rowsBetween(W.unboundedPreceding, 0))
    placed = placed.withColumn("copies", (F.expr("budget div leaf_tokens") + F.when(up_to <= F.expr("budget % leaf_tokens"), 1).otherwise(0)).cast("int"))
    taken = placed.select(*TREE, "id", "tokens", "budget", "copies")
    out = _null_safe_join(rows, taken, [*TREE, "id", "tokens"])
    return out.select("doc.*", F.col("domain").alias("_domain"), F.col("tokens").alias("_tokens"), F.col("budget").alias("_budget"), F.col("copies").alias("_copies"))


def source_domain() -> Column:
    """The domain of a source: its number modulo four; d0 where it has none."""
    return F.concat(F.lit("d"), F.coalesce(F.expr("CAST(try_cast(nullif(regexp_extract(source, '([0-9]{1,9})', 1), '') AS BIGINT) % 4 AS STRING)"), F.lit("0")))


def mix_stage(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """The documents of the mix, each as often as it is taken, with their own columns whatever their names.

    Null and empty texts weigh one token; rows that repeat an id and text tie and are taken in any order; an empty table
    gives no rows.
    """
    mixed = select_mix(spark, docs, source_domain())
    return mixed.filter("_copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies")))).select(*docs.columns)


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "source", "text")
    mixed = select_mix(spark, docs, source_domain())
    return mixed.select("doc_id", F.col("_domain").alias("domain"), "lang", "source", F.col("_tokens").alias("tokens"), F.col("_budget").alias("leaf_budget"), F.col("_copies").alias("copies"))


def _oracle() -> str:
    case = lambda level: "CASE " + " ".join(f"WHEN {level} = '{v}' THEN {w}" for v, w in WEIGHTS[level].items()) + " ELSE 1 END" if level in WEIGHTS else "1"
    sql = [
        "d AS (SELECT doc_id, 'd' || coalesce(CAST(try_cast(nullif(regexp_extract(source, '([0-9]{1,9})', 1), '') AS BIGINT) % 4 AS VARCHAR), '0') AS domain, lang, source, CAST(greatest(1, (strlen(coalesce(text, '')) + 3) // 4) AS BIGINT) AS tokens FROM documents)",
        f"n0 AS (SELECT domain, lang, source, CAST(sum(tokens) AS BIGINT) AS t, CAST(sum(tokens) AS BIGINT) * {EPOCHS} AS cap, least(CAST(floor(CAST(sum(sum(tokens)) OVER () AS DOUBLE) * {SHARE}) AS BIGINT), CAST(sum(sum(tokens)) OVER () AS BIGINT) * {EPOCHS}) AS budget FROM d GROUP BY ALL)",
    ]
    for i, level in enumerate(TREE):
        above = ", ".join(TREE[:i])
        part = f"PARTITION BY {above}" if above else ""
        here = ", ".join(TREE[: i + 1])
        sql += [
            f"g{i} AS (SELECT {here}, CAST(sum(cap) AS BIGINT) AS c, min(budget) AS b, CAST({case(level)} AS BIGINT) AS w FROM n{i} GROUP BY {here})",
            f"r{i} AS (SELECT *, CAST(b - coalesce(sum(c) OVER ({part} ORDER BY c / w, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS DOUBLE) / CAST(sum(w) OVER ({part} ORDER BY c / w, {level} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS DOUBLE) AS rate FROM g{i})",
            f"s{i} AS (SELECT *, least(c, CAST(floor(max(rate) OVER ({part}) * w) AS BIGINT)) AS share FROM r{i})",
            f"n{i + 1} AS (SELECT n.domain, n.lang, n.source, n.t, n.cap, s.share AS budget FROM n{i} n JOIN s{i} s ON " + " AND ".join(f"n.{c} IS NOT DISTINCT FROM s.{c}" for c in TREE[: i + 1]) + ")",
        ]
    sql += [
        f"k AS (SELECT d.*, budget, t, md5('{SEED}:' || CAST(budget // t AS VARCHAR) || ':' || coalesce(CAST(doc_id AS VARCHAR), '') || ':' || CAST(tokens AS VARCHAR)) AS key FROM d JOIN n3 n ON " + " AND ".join(f"d.{c} IS NOT DISTINCT FROM n.{c}" for c in TREE) + ")",
        "p AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY key, CAST(doc_id AS VARCHAR), tokens ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS upto FROM k)",
    ]
    return "WITH " + ",\n".join(sql) + "\nSELECT doc_id, domain, lang, source, tokens, budget AS leaf_budget, CAST(budget // t + CASE WHEN upto <= budget % t THEN 1 ELSE 0 END AS INTEGER) AS copies FROM p"


ORACLE = _oracle()
