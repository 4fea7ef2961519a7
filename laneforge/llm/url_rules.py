"""URL filters: a rule list, and association rules that FP-growth mines from labelled pages.

A url becomes a set of tokens. Frequent token sets that predict a verdict with enough confidence are rules; those that a
shorter rule with the same verdict and no less confidence makes needless are pruned. Tokens that always occur together
are mined as one, so a long url template does not multiply sets. An inverted index files every rule under its rarest
token: a url meets only the rules of its own tokens and checks them for the rest.
"""

from __future__ import annotations

import math

from pyspark.ml.fpm import FPGrowth, PrefixSpan
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from laneforge.session import written

from .common import UPPER, lower_ascii

#: Fixed values of the query: verdict and rule.
RULES = [("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/")]
VERDICT = "verdict="
#: Rules are broadcast up to so many; beyond, they join by a shuffle.
BROADCAST_RULES = 20_000


def host_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path; both empty where the url is null or has no ://."""
    at = F.locate("://", url)
    rest = F.substr(url, at + 3)
    cut = F.regexp_extract(rest, r"^([^/?#]*)", 1)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    none = url.isNull() | (at == 0)
    return F.when(none, "").otherwise(lower_ascii(cut)), F.when(none, "").otherwise(path)


def tokens(url: Column, host: Column, path: Column) -> Column:
    """Distinct tokens of a url: scheme, domains, path words with numbers made alike, query names, fragment."""
    labels = F.filter(F.split(host, r"\."), lambda x: x != "")
    domains = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.concat(F.lit("host:"), F.array_join(F.slice(labels, -i, i), ".")))
    words = F.filter(F.split(F.regexp_replace(F.lower(path), "[0-9]+", "0"), "[^a-z0-9]+"), lambda x: x != "")
    query = F.filter(F.split(F.regexp_extract(url, r"\?([^#]*)", 1), "&"), lambda x: x != "")
    return F.array_distinct(
        F.concat(
            F.array(F.concat(F.lit("scheme:"), F.lower(F.coalesce(F.regexp_extract(url, r"^([A-Za-z][A-Za-z0-9+.-]*)://", 1), F.lit(""))))),
            F.when(F.size(labels) > 0, domains).otherwise(F.array().cast("array<string>")),
            F.transform(words, lambda w: F.concat(F.lit("path:"), w)),
            F.coalesce(F.transform(query, lambda q: F.concat(F.lit("query:"), F.split(q, "=")[0])), F.array().cast("array<string>")),
        )
    )


def token_classes(rows: DataFrame, need: int) -> DataFrame:
    """token, rep for every token of at least `need` rows (items, ...): tokens that occur in the same rows have one rep.

    Tokens are told apart by two independent sums over the hashes of their rows.
    """
    digest = lambda seed: F.pmod(F.xxhash64(F.lit(seed), "items", "verdict"), F.lit(1 << 31))
    found = rows.select(F.explode("items").alias("token"), digest(1).alias("a"), digest(2).alias("b"))
    found = found.groupBy("token").agg(F.count("*").alias("n"), F.sum("a").alias("a"), F.sum("b").alias("b")).filter(F.col("n") >= need)
    alike = found.groupBy("n", "a", "b").agg(F.min("token").alias("rep"), F.collect_list("token").alias("tokens"))
    return alike.select(F.explode("tokens").alias("token"), "rep")


def _as_reps(rows: DataFrame, classes: DataFrame, *keys: str) -> DataFrame:
    """keys and items: of the rows (keys, items) that have any token with a class, the sorted reps."""
    met = rows.select(*keys, F.explode("items").alias("token")).join(classes, "token")
    return met.groupBy(*keys).agg(F.array_sort(F.collect_set("rep")).alias("items"))


def _frequent(spark: SparkSession, rows: DataFrame, need: int, n: int, longest: int, wide: int) -> DataFrame:
    """items, verdict (null: whatever it is), freq: the sorted sets of up to `longest` tokens that at least `need` of the rows (items, verdict) hold.

    FP-growth enumerates the sets of any length, which a row of many tokens makes endless. Where a row has more than
    `wide`, Spark's prefix-projected pattern growth, which ends at a given length, finds the same sets.
    """
    least = (need - 0.5) / n
    if rows.agg(F.max(F.size("items"))).first()[0] <= wide:
        marked = rows.select(F.concat("items", F.array(F.concat(F.lit(VERDICT), "verdict"))).alias("items"))
        sets = FPGrowth(itemsCol="items", minSupport=least, minConfidence=1.0).fit(marked).freqItemsets
        said = lambda x: x.startswith(VERDICT)
        sets = sets.select(F.array_sort(F.filter("items", lambda x: ~said(x))).alias("items"), F.substr(F.get(F.filter("items", said), F.lit(0)), F.lit(len(VERDICT) + 1)).alias("verdict"), "freq")
        return sets.filter(F.size("items").between(1, longest))
    out = None
    for verdict in [None, *sorted(r[0] for r in rows.select("verdict").distinct().collect())]:  # as many as there are verdicts
        part = rows if verdict is None else rows.filter(F.col("verdict") == verdict)
        part = part.select(F.transform("items", lambda x: F.array(x)).alias("sequence"))
        size = n if verdict is None else part.count()
        found = PrefixSpan(minSupport=min(1.0, (need - 0.5) / size), maxPatternLength=longest).findFrequentSequentialPatterns(part)
        found = found.select(F.flatten("sequence").alias("items"), F.lit(verdict).cast("string").alias("verdict"), "freq").filter(F.col("freq") >= need)
        out = found if out is None else out.unionByName(found)
    return out


def mine(spark: SparkSession, labelled: DataFrame, min_support: float = 0.001, min_confidence: float = 0.6, longest: int = 3, least_rows: int = 5, wide: int = 16) -> tuple[DataFrame, DataFrame]:
    """Rules (antecedent, verdict, confidence, support) from rows (items, verdict), and the classes (token, rep) that their tokens stand for.

    A rule's support is at least min_support of the rows and least_rows of them; an antecedent has up to `longest`
    tokens. Only tokens that are frequent on their own are mined, and of tokens that always come together one: a
    rule fits a url that has some token of the class of each of its tokens.
    """
    labelled = written(spark, labelled.filter("verdict IS NOT NULL").select(F.array_distinct(F.coalesce("items", F.array().cast("array<string>"))).alias("items"), "verdict"), "url-labelled")
    n = labelled.count()
    need = max(least_rows, math.ceil(min_support * n - 1e-9))
    classes = written(spark, token_classes(labelled, need), "url-classes")
    none = spark.createDataFrame([], "antecedent array<string>, verdict string, confidence double, support double")
    if classes.isEmpty():
        return none, classes
    numbered = written(spark, labelled.withColumn("row", F.monotonically_increasing_id()), "url-rows")
    rows = written(spark, _as_reps(numbered, classes, "row", "verdict"), "url-transactions")
    sets = written(spark, _frequent(spark, rows, need, n, longest, wide), "url-sets")
    whole = sets.filter("verdict IS NULL").select(F.col("items").alias("antecedent"), F.col("freq").alias("all"))
    rules = sets.filter("verdict IS NOT NULL").select(F.col("items").alias("antecedent"), "verdict", "freq").join(whole, "antecedent")
    rules = rules.select("antecedent", "verdict", (F.col("freq") / F.col("all")).alias("confidence"), (F.col("freq") / F.lit(n)).alias("support")).filter(F.col("confidence") >= min_confidence)
    rules = written(spark, rules, "url-rules")
    shorter = rules.select(F.col("antecedent").alias("part"), F.col("verdict").alias("same"), F.col("confidence").alias("sure"))
    # Each rule looks its own parts up, at most 2^longest of them.
    parts = rules.withColumn("part", F.explode(_proper_parts(F.col("antecedent"), longest)))
    needless = parts.join(shorter, "part").filter("verdict = same AND sure >= confidence").select("antecedent", "verdict").distinct()
    return rules.join(needless, ["antecedent", "verdict"], "left_anti"), classes


def _proper_parts(items: Column, longest: int) -> Column:
    masks = F.sequence(F.lit(1), F.lit((1 << longest) - 2)) if longest > 1 else F.array().cast("array<int>")
    part = lambda m: F.filter(items, lambda x, i: F.call_function("getbit", m, i) == 1)
    return F.filter(F.array_distinct(F.transform(masks, part)), lambda p: (F.size(p) > 0) & (F.size(p) < F.size(items)))


def judge_by_rules(spark: SparkSession, pages: DataFrame, rules: DataFrame, classes: DataFrame, fallback: str = "allow") -> DataFrame:
    """row, items -> row, verdict, confidence: of the rules that hold for a row, the surest; block before allow on ties."""
    rules = written(spark, rules, "url-pruned")
    frequency = rules.select(F.explode("antecedent").alias("token")).groupBy("token").agg(F.count("*").alias("uses"))
    filed = rules.withColumn("rule", F.monotonically_increasing_id())
    rarest = filed.select("rule", F.explode("antecedent").alias("token")).join(frequency, "token").groupBy("rule").agg(F.min_by("token", F.struct("uses", "token")).alias("token"))
    index = written(spark, filed.join(rarest, "rule").groupBy("token").agg(F.collect_list(F.struct("antecedent", "verdict", "confidence", "support")).alias("rules")), "url-index")
    side = F.broadcast(index) if rules.count() <= BROADCAST_RULES else index
    known = _as_reps(pages, classes, "row")
    met = known.select("row", "items", F.explode("items").alias("token")).join(side, "token")
    fits = met.select("row", F.explode(F.filter("rules", lambda r: F.size(F.array_except(r["antecedent"], F.col("items"))) == 0)).alias("r"))
    best = fits.groupBy("row").agg(F.max(F.struct("r.confidence", (F.col("r.verdict") == "block").alias("blocks"), "r.support", "r.verdict")).alias("r"))
    return pages.select("row").join(best, "row", "left").select("row", F.coalesce("r.verdict", F.lit(fallback)).alias("verdict"), F.col("r.confidence").alias("confidence"))


def matched_rule(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits (struct rule, verdict), or null."""
    out = F.lit(None)
    for verdict, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        domain, _, rest = rule.partition("/")
        fits = ((host == domain) | host.endswith("." + domain)) & path.startswith("/" + rest)
        out = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def judge(spark: SparkSession, pages: DataFrame, labels: DataFrame, min_support: float = 0.001, min_confidence: float = 0.6) -> DataFrame:
    """One row per page: page_id, host, path, rule, verdict, confidence.

    pages (page_id, url); labels (doc_id, quality, toxic) for pages of that id: a page is blocked if it is toxic or of
    quality 0, else allowed. A null url has an empty host and path and no tokens but an empty scheme, so mined rules
    seldom fit and the fallback is allow. Urls of any length are read whole. Repeated pages are judged each; repeated
    labels count each; null labels not. Without labels every verdict is a rule's of the list or the fallback; no pages
    give no rows. Other columns are not read.
    """
    host, path = host_path(F.col("url"))
    rows = pages.select("page_id", F.col("url").cast("string").alias("url")).withColumns({"host": host, "path": path})
    rows = rows.withColumn("items", tokens(F.col("url"), F.col("host"), F.col("path"))).withColumn("row", F.coalesce("url", F.lit("")))
    bad = (F.col("toxic") == 1) | (F.col("quality") == 0)
    known = labels.select(F.col("doc_id").alias("page_id"), F.when(bad, "block").otherwise("allow").alias("verdict")).filter("page_id IS NOT NULL")
    rules, classes = mine(spark, rows.join(known, "page_id").select("items", "verdict"), min_support, min_confidence)
    # A url is judged once, however many pages share it.
    urls = rows.groupBy("row").agg(F.first("items").alias("items"))
    mined = judge_by_rules(spark, urls, rules, classes)
    fixed = matched_rule(F.col("host"), F.col("path"))
    return rows.withColumn("fixed", fixed).join(mined, "row", "left").select("page_id", "host", "path", F.col("fixed.rule").alias("rule"), F.coalesce("fixed.verdict", "verdict", F.lit("allow")).alias("verdict"), F.when(F.col("fixed").isNull(), F.col("confidence")).alias("confidence"))


def op1_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark, spark.read.parquet(f"{sf_dir}/pages.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def _oracle(min_support: float = 0.001, min_confidence: float = 0.6, least_rows: int = 5) -> str:
    """All sets of up to three tokens are counted; of those that hold for a page the surest is its verdict. Rules that a shorter one makes needless never change it."""
    fixed = sorted(RULES, key=lambda r: -len(r[1]))
    fits = lambda rule: "(host = '{0}' OR ends_with(host, '.{0}')) AND starts_with(path, '/{1}')".format(*rule.split("/", 1))
    case = lambda column: "CASE " + " ".join(f"WHEN {fits(r[1])} THEN '{r[column]}'" for r in fixed) + " END"
    sets = lambda rows, key: f"SELECT {key}, t AS a, '' AS b, '' AS c FROM {rows} UNION ALL SELECT x.{key}, x.t, y.t, '' FROM {rows} x JOIN {rows} y ON x.{key} = y.{key} AND x.t < y.t UNION ALL SELECT x.{key}, x.t, y.t, z.t FROM {rows} x JOIN {rows} y ON x.{key} = y.{key} AND x.t < y.t JOIN {rows} z ON z.{key} = y.{key} AND y.t < z.t"
    return rf"""
WITH u AS (SELECT page_id, url, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
hp AS (SELECT page_id, url, translate(coalesce(regexp_extract(rest, '^([^/?#]*)', 1), ''), '{UPPER}', '{UPPER.lower()}') AS host, coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM u),
lb AS (SELECT *, list_filter(string_split(host, '.'), lambda x: x <> '') AS labels FROM hp),
tk AS (SELECT page_id, host, path, list_distinct(list_concat(
    ['scheme:' || lower(coalesce(regexp_extract(url, '^([A-Za-z][A-Za-z0-9+.-]*)://', 1), ''))],
    list_transform(range(1, len(labels) + 1), lambda i: 'host:' || array_to_string(labels[len(labels) + 1 - i:], '.')),
    list_transform(list_filter(string_split_regex(regexp_replace(lower(path), '[0-9]+', '0', 'g'), '[^a-z0-9]+'), lambda x: x <> ''), lambda x: 'path:' || x),
    coalesce(list_transform(list_filter(string_split(regexp_extract(url, '\?([^#]*)', 1), '&'), lambda x: x <> ''), lambda x: 'query:' || string_split(x, '=')[1]), []))) AS items FROM lb),
kn AS (SELECT row_number() OVER () AS rid, items, CASE WHEN toxic = 1 OR quality = 0 THEN 'block' ELSE 'allow' END AS verdict FROM tk JOIN labels ON doc_id = page_id),
nn AS (SELECT count(*) AS n, greatest({least_rows}, ceil({min_support} * count(*) - 1e-9)) AS need FROM kn),
fr AS (SELECT t FROM (SELECT unnest(items) AS t FROM kn) GROUP BY t HAVING count(*) >= (SELECT need FROM nn)),
kt AS (SELECT rid, t FROM (SELECT rid, unnest(items) AS t FROM kn) WHERE t IN (SELECT t FROM fr)),
ks AS ({sets("kt", "rid")}),
cn AS (SELECT a, b, c, verdict, count(*) AS both_n FROM ks JOIN kn USING (rid) GROUP BY ALL),
rl AS (SELECT a, b, c, verdict, both_n / sum(both_n) OVER (PARTITION BY a, b, c) AS confidence, both_n FROM cn),
ok AS (SELECT * FROM rl WHERE both_n >= (SELECT need FROM nn) AND confidence >= {min_confidence}),
pt AS (SELECT page_id, t FROM (SELECT page_id, unnest(items) AS t FROM tk) WHERE t IN (SELECT t FROM fr)),
ps AS ({sets("pt", "page_id")}),
best AS (SELECT page_id, verdict, confidence FROM (SELECT page_id, verdict, confidence, row_number() OVER (PARTITION BY page_id ORDER BY confidence DESC, verdict = 'block' DESC, both_n DESC) AS rn FROM ps JOIN ok USING (a, b, c)) WHERE rn = 1)
SELECT tk.page_id, host, path, {case(1)} AS rule, coalesce({case(0)}, best.verdict, 'allow') AS verdict, CASE WHEN ({case(1)}) IS NULL THEN confidence END AS confidence FROM tk LEFT JOIN best USING (page_id)
"""


ORACLE = _oracle()
