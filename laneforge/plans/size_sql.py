"""SQL for the encoded sizes of the codes that go through values one after the other: recursive, from the definition of each layout.

Each function gives the CTEs from v (list_key, chunk_no, i, len, v, block_no, j, whole) to z (list_key, chunk_no, n, bytes).
"""

from __future__ import annotations

from laneforge.functions.layout import EXCEPTION_TENTHS, PAGE_SAMPLE, SPLIT_LENGTHS, WORD_LAYOUTS

C = "list_key, chunk_no"
B = "list_key, chunk_no, block_no"


def bl(v: str) -> str:
    return f"(CASE WHEN {v} = 0 THEN 0 ELSE length(bin({v})) END)"


def tail() -> str:
    """tl: n, and the bytes of the values after the whole blocks."""
    return f"tl AS (SELECT {C}, CAST(sum(CASE WHEN whole THEN 0 ELSE greatest(1, ({bl('v')} + 6) // 7) END) AS BIGINT) AS tail, count(*) AS n FROM v GROUP BY ALL)"


def words(keys: str) -> str:
    """s8 (keys, words): 64-bit words of the sequences sq (keys, i, w, n), w being bits of a value."""
    fits = " ".join(f"WHEN max(w) OVER (PARTITION BY {keys} ORDER BY i ROWS BETWEEN CURRENT ROW AND {count - 1} FOLLOWING) <= {bits} THEN {count}" for count, bits in WORD_LAYOUTS)
    same = " AND ".join(f"j.{k} = st.{k}" for k in keys.split(", "))
    own = ", ".join(f"j.{k}" for k in keys.split(", "))
    return (
        f"st AS MATERIALIZED (SELECT {keys}, CAST(i AS BIGINT) AS i, n, CASE {fits} END AS step FROM sq), "
        f"j AS (SELECT {keys}, CAST(0 AS BIGINT) AS i, CAST(1 AS BIGINT) AS words FROM st WHERE i = 0 UNION ALL SELECT {own}, j.i + st.step, j.words + 1 FROM j JOIN st ON {same} AND st.i = j.i WHERE j.i + st.step < st.n), "
        f"s8 AS (SELECT {keys}, max(words) AS words FROM j GROUP BY ALL)"
    )


def word_code() -> str:
    return f"sq AS (SELECT {C}, i, {bl('v')} AS w, len AS n FROM v), {words(C)}, z AS (SELECT {C}, n, 8 * words AS bytes FROM s8 JOIN (SELECT {C}, count(*) AS n FROM v GROUP BY ALL) USING ({C}))"


def byte_group_code() -> str:
    return (
        f"w AS MATERIALIZED (SELECT {C}, i, greatest(1, ({bl('v')} + 7) // 8) AS l FROM v), "
        f"g AS (SELECT {C}, i, CAST(l AS BIGINT) AS used, CAST(1 AS BIGINT) AS groups FROM w WHERE i = 0 UNION ALL "
        "SELECT w.list_key, w.chunk_no, w.i, CASE WHEN g.used + w.l > 8 THEN w.l ELSE g.used + w.l END, g.groups + CASE WHEN g.used + w.l > 8 THEN 1 ELSE 0 END FROM g JOIN w ON w.list_key = g.list_key AND w.chunk_no = g.chunk_no AND w.i = g.i + 1), "
        f"z AS (SELECT {C}, count(*) AS n, 9 * max(groups) AS bytes FROM g GROUP BY ALL)"
    )


def page_word_code(choice: str) -> str:
    """Page-patched with all high parts in one word-coded array; choice: the CTEs chosen and e."""
    return (
        f"{tail()}, {choice}, nt AS (SELECT {C}, sum(16 * b) AS low, sum(2 + CASE WHEN m > b THEN 1 + c ELSE 0 END) AS notes FROM chosen GROUP BY ALL), "
        f"sq AS (SELECT {C}, row_number() OVER (PARTITION BY {C} ORDER BY block_no, loc) - 1 AS i, {bl('high')} AS w, count(*) OVER (PARTITION BY {C}) AS n FROM e), {words(C)}, "
        f"z AS (SELECT {C}, n, tail + CASE WHEN n >= 128 THEN 4 + low + 4 + (notes + 3) // 4 * 4 + 4 + 8 * coalesce(words, 0) ELSE 0 END AS bytes FROM tl LEFT JOIN nt USING ({C}) LEFT JOIN s8 USING ({C}))"
    )


def linked_code(sized: bool) -> str:
    size = "(CASE WHEN top < 256 THEN 1 WHEN top < 65536 THEN 2 ELSE 4 END)" if sized else "4"
    return (
        f"{tail()}, sm AS (SELECT {C}, {bl('v')} AS w, count(*) AS c FROM v WHERE whole AND i < {PAGE_SAMPLE} GROUP BY ALL), "
        f"tp AS (SELECT {C}, max(w) AS most, sum(c) AS total FROM sm GROUP BY ALL), "
        f"ct AS (SELECT tp.*, b, total * b + 32 * (SELECT coalesce(sum(c), 0) FROM sm WHERE sm.list_key = tp.list_key AND sm.chunk_no = tp.chunk_no AND sm.w > b) AS cost FROM tp, range(33) g(b) WHERE b <= most), "
        f"pw AS (SELECT {C}, CAST(b AS INTEGER) AS b FROM (SELECT *, row_number() OVER (PARTITION BY {C} ORDER BY cost, b DESC) AS rn FROM ct) WHERE rn = 1), "
        f"nat AS (SELECT v.list_key, v.chunk_no, j, v, b, lag(j) OVER (PARTITION BY v.list_key, v.chunk_no, block_no ORDER BY j) AS pj FROM v JOIN pw ON v.list_key = pw.list_key AND v.chunk_no = pw.chunk_no WHERE whole AND {bl('v')} > b), "
        f"ex AS (SELECT {C}, sum(1 + CASE WHEN pj IS NULL THEN 0 ELSE (j - pj - 1) // (1::BIGINT << b) END) AS k, max(v) AS top FROM nat GROUP BY ALL), "
        f"z AS (SELECT {C}, n, tail + CASE WHEN n >= 128 THEN 4 + (4 + 16 * b) * (n // 128) + coalesce({size} * k, 0) ELSE 0 END AS bytes FROM tl LEFT JOIN pw USING ({C}) LEFT JOIN ex USING ({C}))"
    )


def block_code(optimal: bool) -> str:
    above = f"SELECT {B}, CAST(b AS INTEGER) AS b, (SELECT coalesce(sum(cnt), 0) FROM h WHERE h.list_key = t.list_key AND h.chunk_no = t.chunk_no AND h.block_no = t.block_no AND w > b) AS c FROM t, range(33) g(b) WHERE b <= m"
    tried = f"ch AS ({above})" if optimal else f"ch AS (SELECT {B}, min(b) AS b FROM ({above}) WHERE c * 10 <= {EXCEPTION_TENTHS * 128} GROUP BY ALL)"
    keys = f"{B}, b"
    return (
        f"{tail()}, h AS (SELECT {B}, {bl('v')} AS w, count(*) AS cnt FROM v WHERE whole GROUP BY ALL), t AS (SELECT {B}, max(w) AS m FROM h GROUP BY ALL), {tried}, "
        f"x AS (SELECT v.list_key, v.chunk_no, v.block_no, ch.b, j, v.v >> ch.b AS high FROM v JOIN ch ON v.list_key = ch.list_key AND v.chunk_no = ch.chunk_no AND v.block_no = ch.block_no WHERE whole AND {bl('v.v')} > ch.b), "
        f"xx AS (SELECT *, row_number() OVER o - 1 AS r, count(*) OVER (PARTITION BY {keys}) AS c, j - coalesce(lag(j) OVER o, -1) - 1 AS gap FROM x WINDOW o AS (PARTITION BY {keys} ORDER BY j)), "
        f"sq AS (SELECT {keys}, r AS i, {bl('gap')} AS w, 2 * c AS n FROM xx UNION ALL SELECT {keys}, c + r, {bl('high')}, 2 * c FROM xx), {words(keys)}, "
        f"sz AS (SELECT {B}, min(4 + 16 * b + 8 * coalesce(words, 0)) AS size FROM ch LEFT JOIN s8 USING ({keys}) GROUP BY ALL), sm AS (SELECT {C}, sum(size) AS main FROM sz GROUP BY ALL), "
        f"z AS (SELECT {C}, n, tail + coalesce(main, 0) AS bytes FROM tl LEFT JOIN sm USING ({C}))"
    )


def split_code() -> str:
    """Least bits by dynamic programming from the end; l holds those of the next places, nearest first."""
    named = lambda x: f"(CASE WHEN {x} <= 8 THEN {x} WHEN {x} <= 16 THEN ({x} + 1) // 2 * 2 WHEN {x} <= 24 THEN ({x} + 3) // 4 * 4 ELSE 32 END)"
    cost = ", ".join(f"CASE WHEN i + {n} <= len THEN 8 + {n} * {named(f'max(w) OVER (PARTITION BY {C} ORDER BY i ROWS BETWEEN CURRENT ROW AND {n - 1} FOLLOWING)')} END" for n in SPLIT_LENGTHS)
    least = "least(" + ", ".join(f"coalesce(c.costs[{k + 1}] + dp.l[{n}], 4611686018427387904)" for k, n in enumerate(SPLIT_LENGTHS)) + ")"
    return (
        f"w AS (SELECT {C}, i, len, {bl('v')} AS w FROM v), c AS MATERIALIZED (SELECT {C}, CAST(i AS BIGINT) AS i, len, [{cost}]::BIGINT[] AS costs FROM w), "
        f"dp AS (SELECT {C}, CAST(len AS BIGINT) AS i, [0]::BIGINT[] AS l FROM c WHERE i = 0 UNION ALL "
        f"SELECT c.list_key, c.chunk_no, c.i, list_prepend(CAST({least} AS BIGINT), dp.l)[1:{max(SPLIT_LENGTHS)}] FROM dp JOIN c ON c.list_key = dp.list_key AND c.chunk_no = dp.chunk_no AND c.i = dp.i - 1), "
        f"z AS (SELECT {C}, n, 4 + (l[1] + 7) // 8 AS bytes FROM dp JOIN (SELECT {C}, count(*) AS n FROM v GROUP BY ALL) USING ({C}) WHERE i = 0)"
    )
