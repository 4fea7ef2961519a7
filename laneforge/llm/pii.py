"""Personal data: patterns propose spans, checksums confirm them, context words adjust the score.

DataFrame functions only. The text between the matches (split by the same pattern) gives the positions: a span starts
after all gaps and matches before it. Patterns are written with possessive quantifiers and anchored at the start of a
run of characters, so that a long run costs one pass and no recursion.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_LOCAL = "A-Za-z0-9._%+-"
#: Countries by the length of their IBANs.
IBAN = {
    15: "NO", 16: "BE", 18: "DK|FI|FK|FO|GL|NL|SD", 19: "MK|SI", 20: "AT|BA|EE|KZ|LT|LU|MN|XK", 21: "CH|HR|LI|LV", 22: "BG|BH|CR|DE|GB|GE|IE|ME|RS|VA",
    23: "AE|GI|IL|IQ|OM|SO|TL", 24: "AD|CZ|ES|MD|PK|RO|SA|SE|SK|TN|VG", 25: "LY|PT|ST", 26: "IS|TR", 27: "BI|DJ|FR|GR|IT|MC|SM", 28: "AL|AZ|BY|CY|DO|GT|HN|HU|LB|NI|PL|SV",
    29: "BR|EG|PS|QA|UA", 30: "JO|KW|MU|YE", 31: "MT|SC", 32: "LC", 33: "RU",
}
#: The length of a known country ends the span, so a word in capitals or digits after it is not swallowed; other countries take all they can.
_IBAN = "|".join([rf"(?:{c})[0-9]{{2}}(?:\x20?[A-Z0-9]){{{n - 4}}}+" for n, c in IBAN.items()] + [rf"(?!{'|'.join(IBAN.values())})[A-Z]{{2}}[0-9]{{2}}(?:\x20?[A-Z0-9]){{11,30}}+"])
#: Kind: what a text must hold, the pattern, the check of a match m, the score without and with a context word.
KINDS = {
    "email": ("contains(t, '@')", rf"(?:(?<![{_LOCAL}])|\G)[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "true", 0.9, 1.0),
    "ip": ("contains(t, '.')", r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}", "forall(split(m, '[.]'), p -> length(ltrim('0', p)) <= 3 AND CAST(concat('0', right(ltrim('0', p), 3)) AS INT) <= 255)", 0.6, 0.9),
    "card": ("true", r"[0-9](?:[\x20-]?[0-9]){12,}+", "length(replace(replace(m, ' ', ''), '-', '')) <= 19 AND luhn_check(replace(replace(m, ' ', ''), '-', ''))", 0.7, 1.0),
    "phone": ("contains(t, '+')", r"\+[0-9][\x20().0-9-]+[0-9]", "length(regexp_replace(m, '[^0-9]', '')) BETWEEN 9 AND 15", 0.6, 0.9),
    "iban": ("true", rf"(?<![A-Za-z0-9])(?:{_IBAN})(?![A-Za-z0-9])", "aggregate(split(concat(substr(replace(m, ' ', ''), 5), left(m, 4)), ''), 0, (a, c) -> CASE WHEN c = '' THEN a WHEN c >= 'A' THEN (a * 100 + ascii(c) - 55) % 97 ELSE (a * 10 + CAST(c AS INT)) % 97 END) = 1", 0.8, 1.0),
    "secret": ("true", r"(?i)(?<![a-z0-9])(?:api[_-]?key|token|secret|password)['\x22]?\x20{0,3}[=:]\x20{0,3}['\x22]?[a-z0-9+/_=-]{16,}+", "true", 0.8, 1.0),
    "ssn": ("contains(t, '-')", r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", "left(m, 3) NOT IN ('000', '666') AND left(m, 1) <> '9'", 0.3, 0.8),
}
#: Words that make a kind likelier when they come shortly before or after a span.
CONTEXT = {
    "email": "mail|e-mail|contact|write|kontakt|correo|courriel",
    "ip": "ip|address|host|server|adresse|direcci",
    "card": "card|visa|mastercard|credit|karte|carte|tarjeta|payment",
    "phone": "phone|call|tel|fax|mobile|telefon|llama",
    "iban": "iban|account|bank|konto|compte|cuenta",
    "secret": "auth|login|credential|key",
    "ssn": "ssn|social security",
}
#: The kinds whose confirmed spans always count; others count from this score on.
BASE, THRESHOLD, NEAR = ("email", "ip", "card", "phone"), 0.5, 40
#: Matches whose positions are summed together.
RUN = 128


def _matches(kind: str) -> Column:
    """array<struct<n, m, ok, score>> of a kind: a match m, the length n of the gap before it, whether it counts. From the columns of matches, gaps and ends of gaps.

    The words near a match are those of the NEAR characters before it, up to three earlier matches among them, and after it.
    """
    _, _, check, plain, near = KINDS[kind]
    return F.expr(
        f"""transform(
              transform(
                p_{kind},
                (x, i) -> named_struct('n', x.n, 'm', x.m, 'score', CASE WHEN rlike(
                  lower(concat(right(concat(aggregate(slice(p_{kind}, greatest(i - 2, 1), least(i, 3)), '', (a, y) -> concat(a, y.end, y.m)), x.end), {NEAR}), ' ', left(g_{kind}[i + 1], {NEAR}))),
                  '{CONTEXT[kind]}') THEN {near}D ELSE {plain}D END)),
              x -> named_struct('n', x.n, 'm', x.m, 'ok', transform(array(x.m), m -> {check})[0] AND ({str(kind in BASE).lower()} OR x.score >= {THRESHOLD}D), 'score', x.score))"""
    )


def _found(kind: str) -> Column:
    """array<struct<start, end, score, ok>> of the matches of a kind that count.

    Positions are running sums of lengths. They are taken over the matches of a run of RUN, and over the runs, so that a
    text of very many matches does not copy a growing list once for each.
    """
    chunks = f"sequence(0, greatest(size(x_{kind}) - 1, 0) div {RUN})"
    return F.expr(
        f"""filter(flatten(zip_with(
              {chunks},
              aggregate(
                transform({chunks}, k -> aggregate(slice(x_{kind}, k * {RUN} + 1, {RUN}), 0L, (a, x) -> a + x.n + length(x.m))),
                named_struct('at', 0L, 'out', CAST(array() AS ARRAY<BIGINT>)),
                (acc, n) -> named_struct('at', acc.at + n, 'out', concat(acc.out, array(acc.at))),
                acc -> acc.out),
              (k, first) -> aggregate(
                slice(x_{kind}, k * {RUN} + 1, {RUN}),
                named_struct('at', first, 'out', CAST(array() AS ARRAY<STRUCT<start: BIGINT, end: BIGINT, score: DOUBLE, ok: BOOLEAN>>)),
                (acc, x) -> named_struct(
                  'at', acc.at + x.n + length(x.m),
                  'out', concat(acc.out, array(named_struct('start', acc.at + x.n, 'end', acc.at + x.n + length(x.m), 'score', x.score, 'ok', x.ok)))),
                acc -> acc.out))), s -> s.ok)"""
    )


def _with_matches(rows: DataFrame, kinds) -> DataFrame:
    """Columns x_<kind> of _matches() for a text column t."""
    none = F.array().cast("array<string>")
    rows = rows.withColumns({f"m_{kind}": F.when(F.expr(KINDS[kind][0]), F.regexp_extract_all("t", F.lit(KINDS[kind][1]), F.lit(0))).otherwise(none) for kind in kinds})
    rows = rows.withColumns({f"g_{kind}": F.when(F.size(f"m_{kind}") > 0, F.split("t", KINDS[kind][1], -1)).otherwise(none) for kind in kinds})
    ends = lambda kind: F.expr(f"zip_with(slice(g_{kind}, 1, size(m_{kind})), m_{kind}, (g, m) -> named_struct('n', CAST(length(g) AS BIGINT), 'm', m, 'end', right(g, {NEAR})))")
    rows = rows.withColumns({f"p_{kind}": ends(kind) for kind in kinds})
    return rows.withColumns({f"x_{kind}": _matches(kind) for kind in kinds})


def spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and, for each kind, array<struct<start, end, score, ok>> in code points, end exclusive, in order of start.

    A null or empty text has no spans; a text of any length is read whole. Rows with null or repeated ids are returned as they stand; other columns are
    not read; an empty table gives no rows.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t"))
    return _with_matches(rows, KINDS).select("id", *[_found(kind).alias(kind) for kind in KINDS])


def _listed(kinds) -> Column:
    shown = lambda kind: F.transform(kind, lambda s: F.concat_ws(":", F.lit(kind), s["start"], s["end"]))
    return F.concat_ws(",", *map(shown, kinds))


def redact(docs: DataFrame, text_col: str = "text", out_col: str = "redacted", kinds=tuple(KINDS)) -> DataFrame:
    """All columns and the text with every confirmed span of the kinds replaced by its kind in brackets, one kind after the other.

    A match that fails its check, or that no context makes likely enough, stays. A null text becomes empty. A column
    out_col gives way; rows that repeat are each done; an empty table gives no rows.
    """
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns if c != out_col])
    rows = docs.select(whole.alias("doc"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("t"))
    for kind in kinds:
        rows = _with_matches(rows, [kind])
        done = F.expr(f"concat(array_join(zip_with(slice(g_{kind}, 1, size(m_{kind})), x_{kind}, (g, x) -> concat(g, CASE WHEN x.ok THEN '[{kind}]' ELSE x.m END)), ''), element_at(g_{kind}, -1))")
        rows = rows.withColumn("t", F.when(F.size(f"m_{kind}") > 0, done).otherwise(F.col("t"))).select("doc", "t")
    return rows.select("doc.*", F.col("t").alias(out_col))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = spans(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select(
        F.col("id").alias("doc_id"),
        *[F.size(kind).cast("long").alias(f"n_{kind}") for kind in BASE],
        F.sha2(_listed(BASE).cast("binary"), 256).alias("base_sha256"),
        _listed(KINDS).alias("spans"),
    )
