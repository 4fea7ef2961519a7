"""The registered queries of the engine and the SQL that must agree with them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from laneforge.functions.codecs import ALL, GENERAL
from laneforge.functions.exprs import bit_length, join64, split64, unzigzag, zigzag
from laneforge.operators import blocks as B
from laneforge.operators import deltas as D
from laneforge.operators import dictionary, setops, sizes
from laneforge.session import load, written
from laneforge.sources import postings as P
from laneforge.streaming import ingest

from . import measures as M
from . import pipeline
from . import size_sql as size_sql_of
from . import workloads as WL

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

#: Fixed for both sides: bits of v.
BL = "(CASE WHEN {v} = 0 THEN 0 ELSE length(bin({v})) END)"


def bl(v: str) -> str:
    return BL.format(v=v)


def add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def base(source: str) -> str:
    """CTEs p (postings), q (places) and d (deltas) of a source."""
    return f"""p AS ({P.oracle(source)}),
q AS (SELECT list_key, x, row_number() OVER w - 1 AS pos, count(*) OVER (PARTITION BY list_key) AS n FROM p WINDOW w AS (PARTITION BY list_key ORDER BY x)),
r AS (SELECT list_key, x, pos, n, pos // 65536 AS chunk_no, pos % 65536 AS i, least(65536, n - (pos // 65536) * 65536) AS len FROM q),
d AS (SELECT *, x - coalesce(lag(x, 1) OVER w, 0) AS d1, x - coalesce(lag(x, 4) OVER w, 0) AS d4 FROM r WINDOW w AS (PARTITION BY list_key, chunk_no ORDER BY i))"""


def values(source: str, delta: str, block: int) -> str:
    column = {"d1": "d1", "s4": "d4", "none": "x"}[delta]
    return f"WITH {base(source)},\nv AS (SELECT list_key, chunk_no, i, len, {column} AS v, i // {block} AS block_no, i % {block} AS j, i < (len // {block}) * {block} AS whole FROM d)"


def rows(spark: SparkSession, sf: str, source: str, delta: str = "d1") -> DataFrame:
    """list_key, chunk_no, i, len, v of a source."""
    placed = D.positions(P.postings(spark, sf, source))
    if delta == "none":
        return placed.withColumn("v", F.col("x"))
    return D.delta_strided(placed, {"d1": 1, "s4": 4}[delta], "v")


# Postings and dictionaries.
for source in P.NAMES:
    add(
        f"postings_{source}",
        lambda s, d, source=source: P.postings(s, d, source).groupBy("list_key").agg(F.count("*").alias("n"), F.min("x").alias("x_min"), F.max("x").alias("x_max"), F.sum("x").alias("x_sum")),
        f"SELECT list_key, count(*) AS n, min(x) AS x_min, max(x) AS x_max, CAST(sum(x) AS BIGINT) AS x_sum FROM ({P.oracle(source)}) GROUP BY list_key",
    )
add("postings_rejected", lambda s, d: P.rejected(P.postings(s, d, "documents")), f"SELECT count(*) FILTER (x IS NULL) AS nulls, count(*) FILTER (x < 0) AS negative, count(*) FILTER (x >= 4294967296) AS too_large FROM ({P.oracle('documents')})")
for table, column, name in (("part", "p_brand", "brand"), ("part", "p_type", "type"), ("lineitem", "l_returnflag", "returnflag"), ("orders", "o_orderpriority", "priority"), ("events", "event_type", "event_type")):
    add(f"dict_codes_{name}", lambda s, d, t=table, c=column: dictionary.dictionary(load(s, d, t), c), f"SELECT CAST({column} AS VARCHAR) AS value, count(*) AS cnt, row_number() OVER (ORDER BY count(*) DESC, CAST({column} AS VARCHAR)) - 1 AS code FROM {table} WHERE {column} IS NOT NULL GROUP BY {column}")
add(
    "dict_codes_shipdate",
    lambda s, d: dictionary.dictionary(load(s, d, "lineitem").select(F.date_format("l_shipdate", "yyyy-MM-dd").alias("day")), "day"),
    "SELECT strftime(l_shipdate, '%Y-%m-%d') AS value, count(*) AS cnt, row_number() OVER (ORDER BY count(*) DESC, strftime(l_shipdate, '%Y-%m-%d')) - 1 AS code FROM lineitem WHERE l_shipdate IS NOT NULL GROUP BY 1",
)

# Deltas and back.
for source in ("lineitem_supp", "events_type", "documents", "lineitem_line"):
    for stride in (1, 4):
        add(f"delta{stride}_{source}", lambda s, d, source=source, k=stride: D.delta_strided(D.positions(P.postings(s, d, source)), k).select("list_key", "x", "pos", F.col(f"d{k}").alias("delta")), f"WITH {base(source)} SELECT list_key, x, pos, d{stride} AS delta FROM d")
        add(f"undelta{stride}_{source}", lambda s, d, source=source, k=stride: D.undelta_strided(D.delta_strided(D.positions(P.postings(s, d, source)), k).drop("x"), k).select("list_key", "x"), P.oracle(source))
add("positions_by_range", lambda s, d: D.positions(P.postings(s, d, "documents"), "range", 256).groupBy("list_key", "chunk_no").agg(F.count("*").alias("c"), F.max("i").alias("last"), F.max("len").alias("len")), f"SELECT list_key, x // 256 AS chunk_no, count(*) AS c, count(*) - 1 AS last, count(*) AS len FROM ({P.oracle('documents')}) GROUP BY ALL")
add("residual_roundtrip", lambda s, d: D.from_residual_linear(D.residual_linear(D.positions(P.postings(s, d, "lineitem_supp"))).drop("x")).select("list_key", "x"), P.oracle("lineitem_supp"))
add("residual_linear", lambda s, d: D.residual_linear(D.positions(P.postings(s, d, "lineitem_supp"))).groupBy("list_key").agg(F.count("*").alias("n"), F.max(bit_length(F.col("residual"))).alias("m")), f"""WITH {base('lineitem_supp')}, ft AS (SELECT list_key, chunk_no, coalesce(regr_slope(x, i), 0) AS slope, coalesce(regr_intercept(x, i), min(x)) AS start FROM d GROUP BY ALL),
rs AS (SELECT list_key, CAST(x - floor(start + slope * i) AS BIGINT) AS r FROM d JOIN ft USING (list_key, chunk_no)), zz AS (SELECT list_key, CASE WHEN r < 0 THEN -2 * r - 1 ELSE 2 * r END AS z FROM rs)
SELECT list_key, count(*) AS n, max({bl('z')}) AS m FROM zz GROUP BY list_key""")
add(
    "stride_overhead",
    lambda s, d: D.prepared(P.postings(s, d, "lineitem_supp")).agg(F.round(F.avg(bit_length(F.col("d1"))), 6).alias("bits1"), F.round(F.avg(bit_length(F.col("d4"))), 6).alias("bits4")),
    f"WITH {base('lineitem_supp')} SELECT round(avg({bl('d1')}), 6) AS bits1, round(avg({bl('d4')}), 6) AS bits4 FROM d",
)

# Blocks.
for source in ("documents", "lineitem_supp", "events_type"):
    for block in (128, 32):
        sql = values(source, "d1", block) + f" SELECT list_key, chunk_no, block_no, max({bl('v')}) AS m FROM v WHERE whole GROUP BY ALL"
        add(f"block_widths_{block}_{source}", lambda s, d, source=source, b=block: B.widths_by_max(rows(s, d, source), b), sql)
        add(f"block_width_by_or_{block}_{source}", lambda s, d, source=source, b=block: B.widths(rows(s, d, source), b), sql)
HISTOGRAM = "h AS (SELECT list_key, chunk_no, block_no, " + bl("v") + " AS w, count(*) AS cnt FROM v WHERE whole GROUP BY ALL)"
CHOICE = (
    HISTOGRAM
    + """,
t AS (SELECT list_key, chunk_no, block_no, max(w) AS m FROM h GROUP BY ALL),
k AS (SELECT t.*, b, (SELECT coalesce(sum(cnt), 0) FROM h WHERE h.list_key = t.list_key AND h.chunk_no = t.chunk_no AND h.block_no = t.block_no AND w > b) AS c FROM t, range(33) g(b) WHERE b <= m),
o AS (SELECT list_key, chunk_no, block_no, m, b, c, 128 * b + c * (8 + m - b) AS cost, row_number() OVER (PARTITION BY list_key, chunk_no, block_no ORDER BY 128 * b + c * (8 + m - b), b DESC) AS rn FROM k),
chosen AS (SELECT list_key, chunk_no, block_no, CAST(b AS INTEGER) AS b, CAST(m AS INTEGER) AS m, CAST(c AS BIGINT) AS c, CAST(cost AS BIGINT) AS cost FROM o WHERE rn = 1),
e AS (SELECT v.list_key, v.chunk_no, v.block_no, v.j AS loc, v.v >> chosen.b AS high, chosen.m - chosen.b AS bucket FROM v JOIN chosen ON v.list_key = chosen.list_key AND v.chunk_no = chosen.chunk_no AND v.block_no = chosen.block_no WHERE v.whole AND """
    + bl("v.v")
    + " > chosen.b)"
)
for source in ("lineitem_supp", "documents", "events_type"):
    add(f"bitwidth_histogram_{source}", lambda s, d, source=source: B.histogram(rows(s, d, source)), values(source, "d1", 128) + f", {HISTOGRAM} SELECT * FROM h")
    add(f"patch_width_choice_{source}", lambda s, d, source=source: B.width_choice(rows(s, d, source)), values(source, "d1", 128) + f", {CHOICE} SELECT list_key, chunk_no, block_no, b, m, c, cost FROM chosen")
    add(f"patch_exceptions_{source}", lambda s, d, source=source: B.exceptions(rows(s, d, source)), values(source, "d1", 128) + f", {CHOICE} SELECT list_key, chunk_no, block_no, loc, high, bucket FROM e")
for source in ("events_type", "lineitem_supp"):
    for kind, block, lanes in (("scalar", 32, 1), ("vertical", 128, 4)):
        start = "(j * m)" if lanes == 1 else "((j // 4) * m)"
        word = f"({start} // 32)" if lanes == 1 else f"(({start} // 32) * 4 + j % 4)"
        sql = (
            values(source, "d1", block)
            + f""", m AS (SELECT list_key, chunk_no, block_no, max({bl('v')}) AS m FROM v WHERE whole GROUP BY ALL),
a AS (SELECT list_key, chunk_no, block_no, j, v, m FROM v JOIN m USING (list_key, chunk_no, block_no) WHERE whole AND m > 0),
f AS (SELECT list_key, chunk_no, block_no, {word} AS word_no, (v * (1::BIGINT << CAST({start} % 32 AS INTEGER))) & 4294967295 AS part FROM a
      UNION ALL SELECT list_key, chunk_no, block_no, {word} + {lanes} AS word_no, v >> CAST(32 - {start} % 32 AS INTEGER) AS part FROM a WHERE {start} % 32 + m > 32)
SELECT list_key, chunk_no, block_no, CAST(word_no AS INTEGER) AS word_no, bit_or(part) AS word FROM f GROUP BY ALL"""
        )
        add(f"packed_words_{kind}_{source}", lambda s, d, source=source, b=block, k=lanes: B.packed_words(rows(s, d, source), b, k), sql)

        def unpack(s, d, source=source, b=block, k=lanes):
            r = rows(s, d, source)
            return B.unpacked_words(B.packed_words(r, b, k), B.widths(r, b), b, k)

        add(f"unpacked_words_{kind}_{source}", unpack, values(source, "d1", block) + " SELECT list_key, chunk_no, block_no, j, v FROM v WHERE whole")

# Sizes by formula.
VB, BYTES = f"greatest(1, ({bl('v')} + 6) // 7)", f"greatest(1, ({bl('v')} + 7) // 8)"
C = "list_key, chunk_no"


GREEDY = {
    "simple8b": size_sql_of.word_code, "bytegroup8": size_sql_of.byte_group_code, "wordpatch": lambda: size_sql_of.page_word_code(CHOICE), "linkpatch": lambda: size_sql_of.linked_code(False),
    "sizedpatch": lambda: size_sql_of.linked_code(True), "blockpatch10": lambda: size_sql_of.block_code(False), "blockpatchopt": lambda: size_sql_of.block_code(True), "splitvec": size_sql_of.split_code,
}


def size_sql(codec: str, source: str, delta: str) -> str:
    block = {"vpack256": 256, "vpack512": 512, "pack32": 32, "pack16": 16, "pack8": 8}.get(codec, 128)
    head = values(source, delta, block)
    tail = f"tl AS (SELECT {C}, CAST(sum(CASE WHEN whole THEN 0 ELSE {VB} END) AS BIGINT) AS tail, count(*) AS n FROM v GROUP BY ALL)"
    done = " SELECT list_key, CAST(sum(n) AS BIGINT) AS n, CAST(sum(bytes) AS BIGINT) AS n_bytes FROM z GROUP BY list_key"
    if codec in GREEDY:
        return head.replace("WITH ", "WITH RECURSIVE ", 1) + ", " + GREEDY[codec]() + done
    if codec in ("vpack128", "vpack256", "vpack512", "horizpack", "pack32", "pack16", "pack8"):
        meta = 16 if block >= 128 else 4
        return head + f", {tail}, m AS (SELECT {C}, block_no, max({bl('v')}) AS m FROM v WHERE whole GROUP BY ALL), s AS (SELECT {C}, sum(4 * (({block} * m + 31) // 32)) AS body FROM m GROUP BY ALL), z AS (SELECT {C}, n, (n // {block} + {meta - 1}) // {meta} * {meta} + coalesce(body, 0) + tail AS bytes FROM tl LEFT JOIN s USING ({C}))" + done
    if codec in ("bucketpatch", "vpatch"):
        a, u = (16, 128) if codec == "vpatch" else (4, 32)
        pad = lambda x, k: f"(({x} + {k - 1}) // {k} * {k})"
        return head + (
            f", {tail}, {CHOICE}, nt AS (SELECT {C}, sum(16 * b) AS low, sum(2 + CASE WHEN m > b THEN 1 + c ELSE 0 END) AS notes FROM chosen GROUP BY ALL), "
            f"bk AS (SELECT {C}, bucket, count(*) AS k FROM e GROUP BY ALL), hi AS (SELECT {C}, sum({a} + {u // 8} * bucket * ((k + {u - 1}) // {u})) AS high FROM bk GROUP BY ALL), "
            f"z AS (SELECT {C}, n, tail + CASE WHEN n >= 128 THEN {a} + low + {pad('8 + ' + pad('notes', 4), a)} + coalesce(high, 0) ELSE 0 END AS bytes FROM tl LEFT JOIN nt USING ({C}) LEFT JOIN hi USING ({C}))"
        ) + done
    if codec == "tinygroup4":
        return head + f", g AS (SELECT {C}, i // 4 AS g, count(*) AS n, max({bl('v')}) AS m FROM v GROUP BY ALL), z AS (SELECT {C}, sum(n) AS n, count(*) + (sum(4 * m) + 7) // 8 AS bytes FROM g GROUP BY ALL)" + done
    if codec == "golomb_rice":
        mean = bl("(sum(v) OVER (PARTITION BY list_key, chunk_no) // count(*) OVER (PARTITION BY list_key, chunk_no))::BIGINT")
        return head + f", k AS (SELECT {C}, v, greatest(0, {mean} - 1) AS k FROM v), z AS (SELECT {C}, count(*) AS n, 1 + (sum((v >> k) + 1 + k) + 7) // 8 AS bytes FROM k GROUP BY ALL)" + done
    per = {
        "vbyte": f"sum({VB})",
        "groupvarint": f"sum({BYTES}) + (count(*) + 3) // 4",
        "elias_gamma": f"(sum(2 * {bl('(v + 1)')} - 1) + 7) // 8",
        "elias_delta": f"(sum(2 * {bl('length(bin(v + 1))')} - 1 + {bl('(v + 1)')} - 1) + 7) // 8",
        "raw32": "4 * count(*)",
    }[codec]
    return head + f", z AS (SELECT {C}, count(*) AS n, {per} AS bytes FROM v GROUP BY ALL)" + done


SIZE_SOURCES = ["lineitem_supp", "documents", "events_type", "lineitem_line"]
for codec in sizes.FORMULAS:
    for source in SIZE_SOURCES if codec in ("vpack128", "vpatch", "pack32", "bucketpatch") else ["lineitem_supp", "documents"]:
        for delta in ("d1", "s4") if codec in ("vpack128", "vpatch") else ("d1",):
            name = f"size_{codec}{'_s4' if delta == 's4' else ''}_{source}"
            add(name, lambda s, d, c=codec, source=source, m=delta: sizes.encoded_size(rows(s, d, source, m), c), size_sql(codec, source, delta))


# The byte plane: payload sizes, round trips, agreement with the formulas.
def encoded(s: SparkSession, d: str, source: str, codec: str, delta: str = "d1") -> DataFrame:
    return pipeline.encode_chunks(pipeline.build_chunks(P.postings(s, d, source)), codec, delta)


def payload_sizes(s: SparkSession, d: str, source: str, codec: str, delta: str = "d1") -> DataFrame:
    return encoded(s, d, source, codec, delta).groupBy("list_key").agg(F.sum("n").cast("long").alias("n"), F.sum("n_bytes").alias("n_bytes"))


for codec in GENERAL:
    if codec not in sizes.FORMULAS:
        add(f"size_{codec}_lineitem_supp", lambda s, d, c=codec: payload_sizes(s, d, "lineitem_supp", c), size_sql(codec, "lineitem_supp", "d1") if codec in GREEDY else None)
    for delta in ("d1", "s4") if codec in ("vpack128", "vpatch", "bytegroup8") else ("d1",):
        add(f"roundtrip_{codec}_{delta}", lambda s, d, c=codec, m=delta: pipeline.to_postings(pipeline.decode_chunks(encoded(s, d, "lineitem_supp", c, m))), P.oracle("lineitem_supp"))
for source in ("documents", "events_type", "lineitem_line"):
    add(f"roundtrip_vpatch_d1_{source}", lambda s, d, source=source: pipeline.to_postings(pipeline.decode_chunks(encoded(s, d, source, "vpatch"))), P.oracle(source))


def size_agreement(s: SparkSession, d: str) -> DataFrame:
    """Lists whose payloads differ from the formula: none."""
    chunks = written(s, pipeline.build_chunks(P.postings(s, d, "lineitem_supp")), "chunks")
    real = pipeline.payload_bytes(chunks, [(c, m) for c in sizes.FORMULAS for m in ("d1", "s4")]).withColumnRenamed("n_bytes", "real")
    out = None
    for delta in ("d1", "s4"):
        placed = written(s, rows(s, d, "lineitem_supp", delta), "rows")
        for codec in sizes.FORMULAS:
            one = written(s, sizes.encoded_size(placed, codec).select("list_key", "n_bytes"), "formula")
            one = one.select("list_key", F.lit(codec).alias("codec"), F.lit(delta).alias("delta_mode"), "n_bytes")
            out = one if out is None else out.unionByName(one)
    return out.join(real, ["list_key", "codec", "delta_mode"], "left").filter("real IS NULL OR real <> n_bytes").select("codec", "delta_mode", "list_key", "real", "n_bytes")


add("size_agreement", size_agreement, "SELECT '' AS codec, '' AS delta_mode, '' AS list_key, CAST(0 AS BIGINT) AS real, CAST(0 AS BIGINT) AS n_bytes WHERE false")


def zigzag_columns(s: SparkSession, d: str) -> DataFrame:
    """Signed, unsorted values through zig-zag and the code without deltas, in chunks of ranges of the order they come in."""
    line = load(s, d, "lineitem").select(F.col("l_suppkey").cast("string").alias("list_key"), F.col("l_orderkey").alias("o"), (F.col("l_linenumber") - F.lit(4)).cast("long").alias("v"))
    packed = line.groupBy("list_key", F.expr("o div 16384").alias("chunk_no")).agg(F.array_sort(F.collect_list(F.struct("o", "v"))).alias("r"))  # an order has at most seven lines
    none = F.lit(0).cast("long")
    chunks = packed.select("list_key", "chunk_no", F.size("r").alias("n"), none.alias("x_min"), none.alias("x_max"), F.transform("r", lambda t: zigzag(t["v"])).alias("values"))
    back = pipeline.decode_chunks(pipeline.encode_chunks(chunks, "pack32", "none")).select("list_key", "chunk_no", "n", F.transform("values", unzigzag).alias("v"))
    sums = back.select("list_key", "chunk_no", "n", F.aggregate("v", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.posexplode("v").alias("pos", "x")).groupBy("list_key", "chunk_no", "n", "total").agg(F.sum(F.col("pos") * F.col("x")).alias("moment"))
    before = F.coalesce(F.sum("n").over(W.partitionBy("list_key").orderBy("chunk_no").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    sums = sums.withColumn("moment", F.col("moment") + before * F.col("total"))
    return sums.groupBy("list_key").agg(F.sum("n").alias("n"), F.sum("total").alias("total"), F.sum("moment").alias("moment"))


add("zigzag_columns", zigzag_columns, "WITH a AS (SELECT CAST(l_suppkey AS VARCHAR) AS list_key, l_linenumber - 4 AS v, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber) - 1 AS pos FROM lineitem) SELECT list_key, count(*) AS n, CAST(sum(v) AS BIGINT) AS total, CAST(sum(pos * v) AS BIGINT) AS moment FROM a GROUP BY list_key")


def dictionary_packed(s: SparkSession, d: str) -> DataFrame:
    """Bytes of an unsorted dictionary-coded column under codes without deltas, in chunks of the row order of its key."""
    part = load(s, d, "part").select("p_partkey", "p_brand")
    codes = dictionary.coded(part, "p_brand", dictionary.dictionary(part, "p_brand"))
    placed = codes.select(F.lit("brand").alias("list_key"), F.expr("p_partkey div 4096").alias("chunk_no"), "p_partkey", "code")
    r = placed.groupBy("list_key", "chunk_no").agg(F.array_sort(F.collect_list(F.struct("p_partkey", "code"))).alias("r"))
    chunks = r.select("list_key", "chunk_no", F.size("r").alias("n"), F.lit(0).cast("long").alias("x_min"), F.lit(0).cast("long").alias("x_max"), F.transform("r", lambda t: t["code"]).alias("values"))
    return pipeline.encode_chunks(chunks, "vbyte", "none").agg(F.sum("n").cast("long").alias("n"), F.sum("n_bytes").alias("n_bytes"))


add("dictionary_packed", dictionary_packed, f"WITH c AS (SELECT p_brand, row_number() OVER (ORDER BY count(*) DESC, p_brand) - 1 AS v FROM part GROUP BY p_brand) SELECT count(*) AS n, CAST(sum({VB}) AS BIGINT) AS n_bytes FROM part JOIN c USING (p_brand)")


def split64_roundtrip(s: SparkSession, d: str) -> DataFrame:
    """64-bit ids as 32-bit halves: the low halves are lists of their own under each high half."""
    wide = load(s, d, "orders").select((F.col("o_orderkey") * 1_000_003 + F.col("o_custkey")).alias("id"))
    high, low = split64(F.col("id"))
    halves = wide.select(high.cast("string").alias("list_key"), low.alias("x")).distinct()
    back = pipeline.to_postings(pipeline.decode_chunks(pipeline.encode_chunks(pipeline.build_chunks(halves), "vpack128")))
    return back.select(join64(F.col("list_key").cast("long"), F.col("x")).alias("id"))


add("split64_roundtrip", split64_roundtrip, "SELECT DISTINCT o_orderkey * 1000003 + o_custkey AS id FROM orders")


def split16(s: SparkSession, d: str) -> DataFrame:
    """Ids as 16-bit halves: each high half of a list keeps its low halves in two bytes each."""
    rows16 = P.postings(s, d, "lineitem_supp").select("list_key", F.expr("x div 65536").alias("chunk_no"), F.expr("x % 65536").alias("low"))
    grouped = rows16.groupBy("list_key", "chunk_no").agg(F.array_sort(F.collect_list("low")).alias("values"))  # at most 65,536
    chunks = grouped.select("list_key", "chunk_no", F.size("values").alias("n"), (F.col("chunk_no") * 65536 + F.col("values")[0]).alias("x_min"), (F.col("chunk_no") * 65536 + F.element_at("values", -1)).alias("x_max"), "values")
    return pipeline.encode_chunks(chunks, "raw16", "none")


add(
    "split16_sizes",
    lambda s, d: split16(s, d).groupBy("list_key").agg(F.sum("n").alias("n"), F.sum(F.col("n_bytes") + 4).alias("n_bytes")),
    f"WITH g AS (SELECT list_key, x // 65536 AS h, count(*) AS n FROM ({P.oracle('lineitem_supp')}) GROUP BY ALL) SELECT list_key, CAST(sum(n) AS BIGINT) AS n, CAST(sum(n * 2 + 4) AS BIGINT) AS n_bytes FROM g GROUP BY list_key",
)
add("split16_roundtrip", lambda s, d: pipeline.decode_chunks(split16(s, d)).select("list_key", "chunk_no", F.explode("values").alias("low")).select("list_key", (F.col("chunk_no") * 65536 + F.col("low")).alias("x")), P.oracle("lineitem_supp"))

# Measures.
for source in ("documents", "pages", "lineitem_supp", "events_type"):
    ent = f"c AS (SELECT d1, count(*) AS c FROM d GROUP BY d1), t AS (SELECT CAST(sum(c) AS BIGINT) AS n, sum(c * log2(c)) AS s FROM c) SELECT n, round(log2(n) - s / n, 6) AS entropy FROM t"
    add(f"entropy_by_source_{source}", lambda s, d, source=source: M.entropy(D.delta_strided(D.positions(P.postings(s, d, source)))), f"WITH {base(source)}, {ent}")
for source in ("documents", "pages"):
    add(
        f"entropy_by_class_{source}",
        lambda s, d, source=source: M.entropy(D.delta_strided(D.positions(P.postings(s, d, source))).withColumn("K", M.length_class(F.col("n"))), by="K"),
        f"WITH {base(source)}, c AS (SELECT {bl('n')} - 1 AS K, d1, count(*) AS c FROM d GROUP BY ALL), t AS (SELECT K, CAST(sum(c) AS BIGINT) AS n, sum(c * log2(c)) AS s FROM c GROUP BY K) SELECT CAST(K AS INTEGER) AS \"K\", n, round(log2(n) - s / n, 6) AS entropy FROM t",
    )
    add(f"length_classes_{source}", lambda s, d, source=source: M.length_classes(P.postings(s, d, source)), f"WITH l AS (SELECT list_key, count(*) AS n FROM ({P.oracle(source)}) GROUP BY list_key) SELECT CAST({bl('n')} - 1 AS INTEGER) AS \"K\", count(*) AS lists, CAST(sum(n) AS BIGINT) AS ints FROM l GROUP BY 1")
TERMS = "tm AS (SELECT DISTINCT conv_id AS session, t AS term FROM (SELECT conv_id, unnest(string_split_regex(lower(text), '[^\\p{L}\\p{N}]+')) AS t FROM conversations WHERE role = 'user') WHERE t <> ''), ls AS (SELECT list_key, count(*) AS n FROM (" + P.oracle("documents") + ") GROUP BY list_key)"


def lists(s: SparkSession, d: str) -> DataFrame:
    return P.postings(s, d, "documents").groupBy("list_key").agg(F.count("*").alias("n"))


def terms(s: SparkSession, d: str) -> DataFrame:
    return M.query_terms(load(s, d, "conversations"))


WEIGHTS = f"qw AS (SELECT {bl('n')} - 1 AS K, count(*) AS queries FROM tm JOIN ls ON term = list_key GROUP BY 1), ww AS (SELECT K, queries, round(queries / sum(queries) OVER (), 6) AS w FROM qw)"
add("query_weights", lambda s, d: M.query_weights(terms(s, d), lists(s, d)), f"WITH {TERMS}, {WEIGHTS} SELECT CAST(K AS INTEGER) AS \"K\", queries, w FROM ww")
add("query_match_rate", lambda s, d: M.match_rate(terms(s, d), lists(s, d)), f"WITH {TERMS} SELECT count(*) AS terms, count(list_key) AS matched, round(count(list_key) / count(*), 6) AS rate FROM tm LEFT JOIN ls ON term = list_key")

def all_sizes(s: SparkSession, d: str, source: str = "documents") -> DataFrame:
    """list_key, codec, n, n_bytes of the codes of the report, counted in one layout of the deltas."""
    return sizes.report(rows(s, d, source))


def all_sizes_sql(source: str = "documents") -> str:
    return " UNION ALL ".join(f"SELECT list_key, n, n_bytes, '{c}' AS codec FROM ({size_sql(c, source, 'd1')})" for c in sizes.REPORT)


def by_class(s, d, source="documents"):
    return all_sizes(s, d, source).groupBy("codec", M.length_class(F.col("n")).alias("K")).agg(F.sum("n").alias("ints"), F.sum("n_bytes").alias("bytes"))


CLASSES = f"az AS ({all_sizes_sql()}), cl AS (SELECT codec, CAST({bl('n')} - 1 AS INTEGER) AS K, CAST(sum(n) AS BIGINT) AS ints, CAST(sum(n_bytes) AS BIGINT) AS bytes FROM az GROUP BY 1, 2)"
add("bits_by_class", lambda s, d: by_class(s, d).withColumn("bits", F.round(8 * F.col("bytes") / F.col("ints"), 6)), f"WITH {CLASSES} SELECT codec, K AS \"K\", ints, bytes, round(8 * bytes / ints, 6) AS bits FROM cl")
add("weighted_bits", lambda s, d: M.weighted_mean(by_class(s, d), M.query_weights(terms(s, d), lists(s, d)), 8 * F.col("bytes") / F.col("ints"), ["codec"]), f"WITH {CLASSES}, {TERMS}, {WEIGHTS} SELECT codec, round(sum(w * (8 * bytes / ints)) / sum(w), 6) AS weighted FROM cl JOIN ww ON cl.K = ww.K GROUP BY codec")
add("unweighted_bits", lambda s, d: by_class(s, d).groupBy("codec").agg(F.round(8 * F.sum("bytes") / F.sum("ints"), 6).alias("bits")), f"WITH {CLASSES} SELECT codec, round(8 * sum(bytes) / sum(ints), 6) AS bits FROM cl GROUP BY codec")
add("bits_rollup", lambda s, d: by_class(s, d).rollup("codec", "K").agg(F.sum("ints").alias("ints"), F.sum("bytes").alias("bytes")), f"WITH {CLASSES} SELECT codec, K AS \"K\", CAST(sum(ints) AS BIGINT) AS ints, CAST(sum(bytes) AS BIGINT) AS bytes FROM cl GROUP BY ROLLUP (codec, K)")
add("codec_choice_size", lambda s, d: M.choose_codec(all_sizes(s, d)), f"WITH az AS ({all_sizes_sql()}), r AS (SELECT *, row_number() OVER (PARTITION BY list_key ORDER BY n_bytes, codec) AS k FROM az) SELECT list_key, n, codec, n_bytes FROM r WHERE k = 1")
BEST = "bs AS (SELECT list_key, min(n_bytes) AS least FROM az GROUP BY list_key), bc AS (SELECT az.list_key, min(codec) AS codec, least FROM az JOIN bs ON az.list_key = bs.list_key AND n_bytes = least GROUP BY az.list_key, least)"
# Of each list: the code that the policy names, and then the row of that code.
add(
    "codec_choice_hybrid",
    lambda s, d: M.choose_codec(all_sizes(s, d), "hybrid"),
    f"WITH az AS ({all_sizes_sql()}), {BEST}, nm AS (SELECT bc.list_key, CASE WHEN 8 * least / az.n >= 9 THEN 'bytegroup8' ELSE bc.codec END AS codec FROM bc JOIN az ON az.list_key = bc.list_key AND az.codec = bc.codec) SELECT az.list_key, az.n, az.codec, az.n_bytes FROM nm JOIN az ON az.list_key = nm.list_key AND az.codec = nm.codec",
)
add(
    "codec_choice_workload",
    lambda s, d: M.choose_by_workload(all_sizes(s, d), terms(s, d).groupBy(F.col("term").alias("list_key")).agg(F.count("*").alias("queries"))),
    f"WITH az AS ({all_sizes_sql()}), {BEST}, {TERMS}, f AS (SELECT term, count(*) AS q FROM tm GROUP BY term), "
    "g AS (SELECT q, count(*) AS c FROM f GROUP BY q), u AS (SELECT q, sum(q * c) OVER (ORDER BY q DESC) - q * c AS before, sum(q * c) OVER () AS total FROM g), lv AS (SELECT min(q) AS least FROM u WHERE before < 0.8 * total), "
    "nm AS (SELECT bc.list_key, CASE WHEN f.q >= (SELECT least FROM lv) THEN 'vpack128' ELSE bc.codec END AS codec FROM bc LEFT JOIN f ON term = list_key) SELECT az.list_key, az.n, az.codec, az.n_bytes FROM nm JOIN az ON az.list_key = nm.list_key AND az.codec = nm.codec",
)
add("codec_rank", lambda s, d: all_sizes(s, d).groupBy("codec").agg(F.sum("n_bytes").alias("n_bytes")).withColumn("place", F.expr("dense_rank() OVER (ORDER BY n_bytes)")), f"WITH az AS ({all_sizes_sql()}), t AS (SELECT codec, CAST(sum(n_bytes) AS BIGINT) AS n_bytes FROM az GROUP BY codec) SELECT codec, n_bytes, CAST(dense_rank() OVER (ORDER BY n_bytes) AS INTEGER) AS place FROM t")
add(
    "rel_entropy",
    lambda s, d: by_class(s, d).join(M.entropy(D.delta_strided(D.positions(P.postings(s, d, "documents"))).withColumn("K", M.length_class(F.col("n"))), by="K").select("K", "entropy"), "K").filter("entropy > 0").select("codec", "K", F.round(8 * F.col("bytes") / F.col("ints") / F.col("entropy"), 4).alias("rel")),
    f"WITH {CLASSES}, {base('documents')}, c AS (SELECT CAST({bl('n')} - 1 AS INTEGER) AS K, d1, count(*) AS c FROM d GROUP BY ALL), t AS (SELECT K, sum(c) AS n, sum(c * log2(c)) AS s FROM c GROUP BY K), en AS (SELECT K, round(log2(n) - s / n, 6) AS entropy FROM t) SELECT codec, cl.K AS \"K\", round(8 * bytes / ints / entropy, 4) AS rel FROM cl JOIN en ON cl.K = en.K WHERE entropy > 0",
)


# Queries on compressed lists.
def enc(s: SparkSession, d: str, source: str = "lineitem_supp", chunk: int = 128) -> DataFrame:
    """An encoded table in chunks small enough that look-ups have something to skip."""
    return written(s, pipeline.encode_chunks(pipeline.build_chunks(P.postings(s, d, source), chunk=chunk), "vpack128"), "encoded")


LS = P.oracle("lineitem_supp")
both = lambda op: f"SELECT x FROM ({LS}) WHERE list_key = '7' {op} SELECT x FROM ({LS}) WHERE list_key = '8'"
add("intersect_pair", lambda s, d: setops.intersect(enc(s, d), "7", "8"), both("INTERSECT"))
add("intersect_pair_merge", lambda s, d: setops.intersect(enc(s, d), "7", "8", "merge"), both("INTERSECT"))
add("union_query", lambda s, d: setops.union_lists(enc(s, d), ["7", "8"]), both("UNION"))
add("difference_query", lambda s, d: setops.difference(enc(s, d), "7", "8"), both("EXCEPT"))
add("range_on_compressed", lambda s, d: setops.range_lookup(enc(s, d), 2000, 5000), f"SELECT list_key, x FROM ({LS}) WHERE x BETWEEN 2000 AND 5000")
add("count_from_stats", lambda s, d: setops.list_stats(enc(s, d)), f"SELECT list_key, count(*) AS n, min(x) AS x_min, max(x) AS x_max FROM ({LS}) GROUP BY list_key")
add("value_at", lambda s, d: setops.value_at(e := enc(s, d), setops.list_stats(e).select("list_key", F.expr("(n * 2) div 3").alias("pos")), 128), f"WITH {base('lineitem_supp')} SELECT list_key, pos, x FROM q WHERE pos = (n * 2) // 3")
CHUNKED = f"WITH {base('lineitem_supp')}, ck AS (SELECT list_key, pos // 128 AS chunk_no, count(*) AS c, min(x) AS x_min, max(x) AS x_max FROM q GROUP BY ALL)"
add(
    "skip_decoded",
    lambda s, d: setops.overlapping_chunks(enc(s, d), "7", "8"),
    CHUNKED + ", pr AS (SELECT * FROM ck WHERE list_key IN ('7', '8')) SELECT (SELECT count(*) FROM pr a WHERE EXISTS (SELECT 1 FROM pr b WHERE b.list_key <> a.list_key AND b.x_min <= a.x_max AND a.x_min <= b.x_max)) AS decoded, (SELECT count(*) FROM pr) AS total",
)
add(
    "value_at_decoded",
    lambda s, d: setops.value_at_cost(e := enc(s, d), setops.list_stats(e).select("list_key", F.expr("(n * 2) div 3").alias("pos")), 128),
    CHUNKED + ", t AS (SELECT list_key, count(*) AS total FROM q GROUP BY list_key) SELECT t.list_key, (total * 2) // 3 AS pos, c AS decoded, total FROM t JOIN ck ON ck.list_key = t.list_key AND ck.chunk_no = (total * 2) // 3 // 128",
)
add("asof_skip", lambda s, d: setops.floor_lookup(enc(s, d), P.postings(s, d, "lineitem_supp").select("list_key").distinct().withColumn("at", F.lit(4321).cast("long"))), f"SELECT list_key, CAST(4321 AS BIGINT) AS at, max(x) FILTER (x <= 4321) AS x FROM ({LS}) GROUP BY list_key")
add("intersect_query", lambda s, d: setops.conjunctive(enc(s, d, "documents"), terms(s, d)), f"WITH {TERMS}, p AS ({P.oracle('documents')}), need AS (SELECT session, count(*) AS need FROM tm JOIN ls ON term = list_key GROUP BY session), have AS (SELECT session, x, count(*) AS have FROM tm JOIN p ON term = list_key GROUP BY session, x) SELECT session, x FROM have JOIN need USING (session) WHERE have = need")
add("unmatched_terms", lambda s, d: terms(s, d).join(lists(s, d).select(F.col("list_key").alias("term")), "term", "left_anti").select("session", "term"), f"WITH {TERMS} SELECT session, term FROM tm WHERE term NOT IN (SELECT list_key FROM ls)")


# Workloads.
STEM = "CASE " + " ".join(f"WHEN w LIKE '%{e}' AND length(w) >= {len(e) + 3} THEN left(w, length(w) - {len(e)})" for e in WL.ENDINGS) + " ELSE w END"
WEB = (
    "wd AS (SELECT page_id, unnest(string_split_regex(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^\\p{L}\\p{N}]+')) AS w FROM pages), "
    f"st AS (SELECT DISTINCT {STEM} AS list_key, page_id AS x FROM wd WHERE w <> '' AND w NOT IN (" + ", ".join(f"'{w}'" for w in WL.STOP_WORDS) + ")), "
    "fq AS (SELECT list_key FROM st GROUP BY list_key ORDER BY count(*) DESC, list_key LIMIT 500)"
)
add("web_postings_top", lambda s, d: WL.web_postings(load(s, d, "pages"), 500).groupBy("list_key").agg(F.count("*").alias("n"), F.sum("x").alias("x_sum")), f"WITH {WEB} SELECT list_key, count(*) AS n, CAST(sum(x) AS BIGINT) AS x_sum FROM st WHERE list_key IN (SELECT list_key FROM fq) GROUP BY list_key")
# Digests of the orders' keys: their low bits are uniform at every width.
add("packing_speeds", lambda s, d: WL.packing_speeds(load(s, d, "orders"), F.crc32(F.col("o_orderkey").cast("string"))))
PAPER_CODES = [("vpack128", "s4"), ("vpack128", "d1"), ("vpatch", "s4"), ("vpatch", "d1"), ("bytegroup8", "s4"), ("bytegroup8", "d1"), *[(c, "d1") for c in ("linkpatch", "sizedpatch", "bucketpatch", "wordpatch", "pack32", "blockpatch10", "blockpatchopt", "simple8b", "splitvec", "vbyte")]]


def code_table(s: SparkSession, d: str) -> DataFrame:
    return WL.all_codes(written(s, pipeline.build_chunks(P.postings(s, d, "lineitem_line")), "lists"), PAPER_CODES)


def with_cycles(table: DataFrame) -> DataFrame:
    return table.crossJoin(F.broadcast(WL.clock(table.sparkSession))).withColumn("decoding_cycles", WL.cycles(F.col("decoding_mis"), F.col("mhz"))).drop("mhz")


add("code_table", lambda s, d: with_cycles(code_table(s, d)))
add("copy_ceiling", lambda s, d: WL.copy_speed(load(s, d, "lineitem"), F.col("l_orderkey")))
add("buffer_memory", lambda s, d: WL.buffer_memory(written(s, pipeline.build_chunks(P.postings(s, d, "lineitem_line")), "lists"), PAPER_CODES))


def chunk_lists(s: SparkSession, d: str, source: str) -> DataFrame:
    return written(s, pipeline.build_text_chunks(P.words_by_id(s, d, source)), "lists")


def class_table(s: SparkSession, d: str, source: str) -> DataFrame:
    """Integers, bytes and times of every code by class of length."""
    return pipeline.measure_classes(chunk_lists(s, d, source), PAPER_CODES)


def weighted_table(s: SparkSession, d: str, source: str) -> DataFrame:
    chunks = chunk_lists(s, d, source)
    fetched = M.query_weights(terms(s, d), chunks.groupBy("list_key").agg(F.sum("n").cast("long").alias("n")))
    return written(s, M.weighted_table(pipeline.measure_classes(chunks, PAPER_CODES), fetched), "weighted")


for source in ("documents", "pages"):
    speeds = lambda s, d, source=source: class_table(s, d, source).select("codec", "delta_mode", "K", "n_ints", (8 * F.col("n_bytes") / F.col("n_ints")).alias("bits"), (1000 * F.col("n_ints") / F.col("coding_ns")).alias("coding_mis"), (1000 * F.col("n_ints") / F.col("decoding_ns")).alias("decoding_mis"))
    add(f"speeds_by_class_{source}", speeds)
    add(f"weighted_table_{source}", lambda s, d, source=source: weighted_table(s, d, source))
    add(f"weighted_frontier_{source}", lambda s, d, source=source: WL.frontier(weighted_table(s, d, source), "weighted_bits", "weighted_coding_mis", "weighted_decoding_mis"))
add("weighting_gap", lambda s, d: M.weighting_gap(weighted_table(s, d, "documents")))
add("coding_gap", lambda s, d: M.coding_gap(weighted_table(s, d, "documents")))
add(
    "fused_speeds",
    lambda s, d: (lambda c: pipeline.measured(c, "vpack128", "s4", 3, fused=True).withColumn("way", F.lit("fused")).unionByName(pipeline.measured(c, "vpack128", "s4", 3).withColumn("way", F.lit("two passes"))).select("way", "delta_mode", "decoding_mis"))(written(s, WL.synthetic(s, "uniform", "long", 64), "synthetic")),
)
for delta in ("d1", "s4"):
    add(f"fused_roundtrip_{delta}", lambda s, d, m=delta: pipeline.to_postings(pipeline.decode_chunks(encoded(s, d, "lineitem_supp", "vpack128", m), fused=True)), P.oracle("lineitem_supp"))
# Columns of a database under all codes of the report.
for source in ("orders_cust", "events_user", "lineitem_part", "events_type"):
    add(
        f"column_bits_{source}",
        lambda s, d, source=source: all_sizes(s, d, source).groupBy("codec").agg(F.sum("n").alias("n"), F.sum("n_bytes").alias("n_bytes"), F.round(8 * F.sum("n_bytes") / F.sum("n"), 6).alias("bits")),
        f"WITH az AS ({all_sizes_sql(source)}) SELECT codec, CAST(sum(n) AS BIGINT) AS n, CAST(sum(n_bytes) AS BIGINT) AS n_bytes, round(8 * sum(n_bytes) / sum(n), 6) AS bits FROM az GROUP BY codec",
    )


def parquet_bits(s: SparkSession, d: str) -> DataFrame:
    """Bits an integer of long lists of ids in Parquet's own integer codings, beside those of this engine: ids as they are for Parquet, deltas for the others."""
    chunks = written(s, pipeline.build_chunks(P.postings(s, d, "lineitem_line")), "lists")
    return WL.all_codes(chunks, [("parquet_delta", "none"), ("parquet_dictionary", "none"), ("vpack128", "d1"), ("vpatch", "d1"), ("vbyte", "d1")]).select("codec", "delta_mode", "n_ints", "bits_per_int", "coding_mis", "decoding_mis")


add("parquet_bits", parquet_bits)
add("code_frontier", lambda s, d: WL.frontier(written(s, code_table(s, d), "codes")))
add(
    "events_in_intervals",
    lambda s, d: WL.in_intervals(P.postings(s, d, "events_user"), s.range(0, 40).select(F.col("id").alias("name"), (F.col("id") * 60_000).alias("lo"), (F.col("id") * 60_000 + 90_000).alias("hi")), 100_000).groupBy("name").agg(F.count("*").alias("n")),
    f"SELECT name, count(*) AS n FROM ({P.oracle('events_user')}) JOIN (SELECT range AS name, range * 60000 AS lo, range * 60000 + 90000 AS hi FROM range(40)) ON x BETWEEN lo AND hi GROUP BY name",
)
for delta in ("d1", "s4"):
    add(f"weighted_mean_by_class_{delta}", lambda s, d, m=delta: M.weighted_mean(M.by_class(sizes.encoded_size(rows(s, d, "documents", m), "vpack128")).withColumn("codec", F.lit("vpack128")), M.query_weights(terms(s, d), lists(s, d)), 8 * F.col("bytes") / F.col("ints"), ["codec"]), f"WITH az AS ({size_sql('vpack128', 'documents', delta)}), cl AS (SELECT CAST({bl('n')} - 1 AS INTEGER) AS K, sum(n) AS ints, sum(n_bytes) AS bytes FROM az GROUP BY 1), {TERMS}, {WEIGHTS} SELECT 'vpack128' AS codec, round(sum(w * (8 * bytes / ints)) / sum(w), 6) AS weighted FROM cl JOIN ww ON cl.K = ww.K")


# Aggregates of every shape, and sketches held against exact answers.
DAY = "strftime(ts, '%Y-%m-%d')"


def daily_events(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "events").select("event_type", F.date_format("ts", "yyyy-MM-dd").alias("day"), "user_id", "event_id", "value", "props")


add("events_cube", lambda s, d: daily_events(s, d).cube("event_type", "day").agg(F.count("*").alias("n"), F.max("event_id").alias("last")), f"SELECT event_type, {DAY} AS day, count(*) AS n, max(event_id) AS last FROM events GROUP BY CUBE (event_type, {DAY})")
add("events_grouping_sets", lambda s, d: daily_events(s, d).groupingSets([("event_type",), ("day",)], "event_type", "day").agg(F.count("*").alias("n")), f"SELECT event_type, {DAY} AS day, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type), ({DAY}))")
PIVOT = ["vpack128", "vpatch", "vbyte"]
add(
    "bits_pivot",
    lambda s, d: by_class(s, d, "lineitem_supp").groupBy("K").pivot("codec", PIVOT).agg(F.first("bytes")),
    f"WITH az AS ({all_sizes_sql('lineitem_supp')}) SELECT CAST({bl('n')} - 1 AS INTEGER) AS \"K\", " + ", ".join(f"CAST(sum(n_bytes) FILTER (codec = '{c}') AS BIGINT) AS {c}" for c in PIVOT) + " FROM az GROUP BY 1",
)
add(
    "events_unpivot",
    lambda s, d: load(s, d, "events").select("event_id", "user_id", F.second("ts").cast("long").alias("second")).unpivot("event_id", ["user_id", "second"], "measure", "v").groupBy("measure").agg(F.count("*").alias("n"), F.sum("v").alias("total")),
    "SELECT measure, count(*) AS n, CAST(sum(v) AS BIGINT) AS total FROM (SELECT 'user_id' AS measure, user_id AS v FROM events UNION ALL SELECT 'second', extract(second FROM ts) FROM events) GROUP BY measure",
)
add("json_postings", lambda s, d: P.postings_from_column(daily_events(s, d), F.get_json_object("props", "$.k"), F.col("event_id")), "SELECT DISTINCT json_extract_string(props, '$.k') AS list_key, event_id AS x FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL")


def sketches(s: SparkSession, d: str) -> DataFrame:
    """Of each source: exact numbers, and whether the sketches come as near as they promise."""
    out = None
    for source in ("lineitem_supp", "documents"):
        ids = P.postings(s, d, source)
        one = ids.agg(
            F.count_distinct("x").alias("ids"), F.count_distinct("list_key").alias("lists"), F.approx_count_distinct("x", 0.02).alias("ax"), F.hll_sketch_estimate(F.hll_sketch_agg("list_key", F.lit(14))).alias("al"),
            F.percentile_approx("x", 0.5, 10_000).alias("am"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY x)").cast("long").alias("median"), F.max("x").alias("top"),
        )
        near = lambda a, b, share: F.abs(F.col(a) - F.col(b)) <= share * F.col(b)
        one = one.select(F.lit(source).alias("source"), "ids", "lists", near("ax", "ids", 0.1).alias("ids_near"), near("al", "lists", 0.05).alias("lists_near"), (F.abs(F.col("am") - F.col("median")) <= 0.01 * F.col("top")).alias("median_near"))
        out = one if out is None else out.unionByName(one)
    return out


add("sketches", sketches, " UNION ALL ".join(f"SELECT '{x}' AS source, count(DISTINCT x) AS ids, count(DISTINCT list_key) AS lists, true AS ids_near, true AS lists_near, true AS median_near FROM ({P.oracle(x)})" for x in ("lineitem_supp", "documents")))


def payload_checksums(s: SparkSession, d: str) -> DataFrame:
    """Payloads that are not what their checksum says after they were written and read: none of all."""
    table = encoded(s, d, "lineitem_supp", "vpatch").withColumn("crc", F.crc32("payload")).withColumn("xx", F.xxhash64("payload"))
    return written(s, table, "checked").agg(F.count("*").alias("payloads"), F.count_if((F.crc32("payload") != F.col("crc")) | (F.xxhash64("payload") != F.col("xx"))).alias("damaged"))


add("payload_checksums", payload_checksums, f"SELECT count(DISTINCT list_key) AS payloads, 0::BIGINT AS damaged FROM ({P.oracle('lineitem_supp')})")


# Streams: over the files of the table until nothing is left, and the same functions on the batch.
def event_files(s: SparkSession, d: str) -> DataFrame:
    return ingest.event_stream(s, f"{d}/events.parquet")


DAILY = "SELECT event_type AS list_key, strftime(ts, '%Y-%m-%d') AS day, count(*) AS n, min(event_id) AS x_min, max(event_id) AS x_max FROM events GROUP BY 1, 2"
add("daily_counts", lambda s, d: ingest.daily_counts(load(s, d, "events")), DAILY)
add("stream_daily_counts", lambda s, d: ingest.drained(s, ingest.daily_counts(event_files(s, d)), "daily", "complete"), DAILY)
add(
    "daily_encode",
    lambda s, d: ingest.daily_lists(load(s, d, "events")).groupBy("list_key").agg(F.sum("n").alias("n"), F.min("x_min").alias("x_min"), F.max("x_max").alias("x_max"), F.sum("n_bytes").alias("n_bytes")),
    size_sql("vpack128", "events_daily", "d1").replace(" SELECT list_key, CAST(sum(n)", ", zz AS (SELECT list_key, CAST(sum(n)") + ") SELECT list_key, n, x_min, x_max, n_bytes FROM zz JOIN (SELECT list_key, min(x) AS x_min, max(x) AS x_max FROM p GROUP BY list_key) USING (list_key)",
)
add(
    "stream_sessions",
    lambda s, d: ingest.sessions(load(s, d, "events")).drop("start"),
    "WITH a AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events), b AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sn FROM a) SELECT user_id, count(*) AS n, min(event_id) AS x_min, max(event_id) AS x_max FROM b GROUP BY user_id, sn",
)
add(
    "stream_static_join",
    lambda s, d: ingest.drained(s, ingest.with_names(event_files(s, d).select("event_id", (F.col("user_id") % 25).cast("int").alias("n_nationkey")), load(s, d, "nation").select("n_nationkey", "n_name"), "n_nationkey").select("event_id", "n_name"), "named").groupBy("n_name").agg(F.count("*").alias("n"), F.sum("event_id").alias("id_sum")),
    "SELECT n_name, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS id_sum FROM events LEFT JOIN nation ON user_id % 25 = n_nationkey GROUP BY n_name",
)
add("stream_distinct", lambda s, d: ingest.drained(s, ingest.distinct_events(event_files(s, d)).select("event_id"), "distinct"), "SELECT DISTINCT event_id FROM events")

# Synthetic sets at a part of the published size (WL.synthetic with scale 1 is the whole): all codes, both regimes. Tests hold bits against the published ones.
for kind in ("uniform", "clustered"):
    for regime, scale in (("short", 256), ("long", 256)):
        add(f"synthetic_{kind}_{regime}", lambda s, d, kind=kind, regime=regime, k=scale: WL.all_codes(written(s, WL.synthetic(s, kind, regime, k), "synthetic"), [*PAPER_CODES, ("generic_snappy", "d1")]))


def flagship(s: SparkSession, d: str) -> DataFrame:
    """Lists of suppliers: n, bytes and bits per integer under vertical binary packing."""
    return sizes.encoded_size(rows(s, d, "lineitem_supp"), "vpack128").withColumn("bits_per_int", F.round(8 * F.col("n_bytes") / F.col("n"), 6))


add("flagship", flagship, f"SELECT list_key, n, n_bytes, round(8 * n_bytes / n, 6) AS bits_per_int FROM ({size_sql('vpack128', 'lineitem_supp', 'd1')})")
