"""Measures: entropy, classes of length, query weights, means, ratios, the frontier of size and speed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from laneforge.functions.exprs import bit_length


def length_class(n: Column) -> Column:
    """K for lists of 2^K to 2^(K+1) - 1 ids."""
    return bit_length(n) - 1


def length_classes(rows: DataFrame) -> DataFrame:
    """K, lists, ints from rows with n (any number for each list)."""
    lists = rows.groupBy("list_key").agg(F.count("*").alias("n"))
    return lists.groupBy(length_class(F.col("n")).alias("K")).agg(F.count("*").alias("lists"), F.sum("n").alias("ints"))


def entropy(rows: DataFrame, value: str = "d1", by: str | None = None) -> DataFrame:
    """Shannon entropy (bits) of the values, each an outcome: n, entropy, for every value of `by`.

    Frequencies combine before the shuffle; H = log2 N - sum(c log2 c) / N needs one more sum and no second pass.
    """
    keys = [by] if by else []
    counts = rows.groupBy(*keys, value).agg(F.count("*").alias("c"))
    sums = counts.groupBy(*keys).agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.log2("c")).alias("s"))
    return sums.select(*keys, "n", F.round(F.log2("n") - F.col("s") / F.col("n"), 6).alias("entropy"))


def query_terms(conversations: DataFrame) -> DataFrame:
    """session, term: the words of users' turns, once in a session."""
    from laneforge.sources.postings import words_of

    return conversations.filter("role = 'user'").select(F.col("conv_id").alias("session"), F.explode(words_of(F.col("text"))).alias("term")).distinct()


def query_weights(terms: DataFrame, lists: DataFrame) -> DataFrame:
    """K, queries, w: how likely a query's list is of class K. lists: list_key, n."""
    met = terms.join(lists.select(F.col("list_key").alias("term"), "n"), "term")
    by_class = met.groupBy(length_class(F.col("n")).alias("K")).agg(F.count("*").alias("queries"))
    return by_class.select("K", "queries", F.round(F.col("queries") / F.sum("queries").over(W.partitionBy()), 6).alias("w"))


def match_rate(terms: DataFrame, lists: DataFrame) -> DataFrame:
    found = terms.join(lists.select(F.col("list_key").alias("term"), F.lit(1).alias("hit")), "term", "left")
    return found.agg(F.count("*").alias("terms"), F.count("hit").alias("matched")).withColumn("rate", F.round(F.col("matched") / F.col("terms"), 6))


def by_class(sizes: DataFrame) -> DataFrame:
    """Sizes of lists (list_key, n, n_bytes) -> K, ints, bytes."""
    return sizes.groupBy(length_class(F.col("n")).alias("K")).agg(F.sum("n").alias("ints"), F.sum("n_bytes").alias("bytes"))


def weighted_mean(metrics: DataFrame, weights: DataFrame, metric: Column, by: list[str]) -> DataFrame:
    """sum(w metric) / sum(w) over classes; at most 33 classes are broadcast."""
    return metrics.join(F.broadcast(weights.select("K", "w")), "K").groupBy(*by).agg(F.round(F.sum(F.col("w") * metric) / F.sum("w"), 6).alias("weighted"))


def pareto(df: DataFrame, bits: str = "bits_per_int", speed: str = "decoding_mis", name: str = "codec") -> DataFrame:
    """The schemes that no other beats in one measure without losing in the other. One row a scheme: small on either side."""
    other = df.select(F.col(bits).alias("ob"), F.col(speed).alias("os"), F.col(name).alias("on"))
    beats = (F.col("ob") <= F.col(bits)) & (F.col("os") >= F.col(speed)) & ((F.col("ob") < F.col(bits)) | (F.col("os") > F.col(speed))) & (F.col("on") != F.col(name))
    return df.join(F.broadcast(other), beats, "left_anti")


def choose_codec(sizes: DataFrame, policy: str = "size", threshold_bits: float = 9.0, fast: str = "bytegroup8") -> DataFrame:
    """list_key, n, codec, n_bytes: one code for each list from rows (list_key, codec, n, n_bytes), and its bytes.

    `size`: the fewest bytes. `hybrid`: the fast byte code where nothing gets below the threshold of bits, the
    smallest elsewhere and where the fast code has no row. Ties go to the name that sorts first.
    """
    if policy not in ("size", "hybrid"):
        raise ValueError("policy is 'size' or 'hybrid'")
    best = _best_and(sizes, fast)
    take_fast = F.lit(policy == "hybrid") & F.col("fast_bytes").isNotNull() & (8 * F.col("n_bytes") / F.col("n") >= threshold_bits)
    return _take(best, take_fast, fast)


def _best_and(sizes: DataFrame, fast: str) -> DataFrame:
    """The smallest code of each list, and the bytes of the fast one beside it, in one pass."""
    best = sizes.groupBy("list_key").agg(F.min(F.struct("n_bytes", "codec", "n")).alias("b"), F.max(F.when(F.col("codec") == fast, F.col("n_bytes"))).alias("fast_bytes"))
    return best.select("list_key", "b.n", F.col("b.codec").alias("codec"), F.col("b.n_bytes").alias("n_bytes"), "fast_bytes")


def _take(best: DataFrame, take_fast: Column, fast: str) -> DataFrame:
    return best.select("list_key", "n", F.when(take_fast, fast).otherwise(F.col("codec")).alias("codec"), F.when(take_fast, F.col("fast_bytes")).otherwise(F.col("n_bytes")).alias("n_bytes"))


def choose_by_workload(sizes: DataFrame, fetches: DataFrame, hot_share: float = 0.8, fast: str = "vpack128") -> DataFrame:
    """Lists that together get `hot_share` of all fetches take the fast code, others the smallest, each with its bytes. fetches: list_key, queries."""
    total = fetches.agg(F.sum("queries").alias("all"))
    heat = fetches.groupBy("queries").agg(F.count("*").alias("lists"))
    # Lists are cut by how often they are fetched: one running sum over the few different counts.
    heat = heat.withColumn("before", F.sum(F.col("queries") * F.col("lists")).over(W.partitionBy().orderBy(F.desc("queries"))) - F.col("queries") * F.col("lists"))
    level = heat.crossJoin(F.broadcast(total)).filter(F.col("before") < hot_share * F.col("all")).agg(F.min("queries").alias("least"))
    hot = fetches.crossJoin(F.broadcast(level)).filter("queries >= least").select("list_key", F.lit(True).alias("hot"))
    best = _best_and(sizes, fast).join(hot, "list_key", "left")
    return _take(best, F.coalesce("hot", F.lit(False)) & F.col("fast_bytes").isNotNull(), fast)


def weighted_table(by_class: DataFrame, weights: DataFrame) -> DataFrame:
    """codec, delta_mode, and for bits, coding and decoding speed the mean over all integers and the mean weighted by what queries fetch.

    by_class: rows (codec, delta_mode, K, n_ints, n_bytes, coding_ns, decoding_ns). A class's weight is the share of
    queries whose list is of that class; its metrics are those of all its integers together.
    """
    metrics = {"bits": 8 * F.col("n_bytes") / F.col("n_ints"), "coding_mis": 1000 * F.col("n_ints") / F.col("coding_ns"), "decoding_mis": 1000 * F.col("n_ints") / F.col("decoding_ns")}
    total = lambda c: F.sum(c)
    plain = {"bits": 8 * total("n_bytes") / total("n_ints"), "coding_mis": 1000 * total("n_ints") / total("coding_ns"), "decoding_mis": 1000 * total("n_ints") / total("decoding_ns")}
    met = by_class.join(F.broadcast(weights.select("K", "w")), "K", "left").withColumn("w", F.coalesce("w", F.lit(0.0)))  # at most 33 classes
    return met.groupBy("codec", "delta_mode").agg(*[x.alias(name) for name, x in plain.items()], *[(F.sum(F.col("w") * x) / F.sum("w")).alias(f"weighted_{name}") for name, x in metrics.items()])


def weighting_gap(table: DataFrame) -> DataFrame:
    """How far the weighted means lie from the plain ones, as a share of these."""
    gap = lambda m: (F.abs(F.col(f"weighted_{m}") - F.col(m)) / F.col(m)).alias(f"{m}_gap")
    return table.select("codec", "delta_mode", gap("bits"), gap("coding_mis"), gap("decoding_mis"))


def coding_gap(table: DataFrame) -> DataFrame:
    """How many times slower a code codes than it decodes, and than the fastest coder codes."""
    fastest = table.agg(F.max("weighted_coding_mis").alias("fastest"))
    return table.crossJoin(F.broadcast(fastest)).select("codec", "delta_mode", "weighted_coding_mis", "weighted_decoding_mis", (F.col("weighted_decoding_mis") / F.col("weighted_coding_mis")).alias("decoding_per_coding"), (F.col("fastest") / F.col("weighted_coding_mis")).alias("lag"))
