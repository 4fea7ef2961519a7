"""The pipeline against plain versions of its stages, one after the other."""

from collections import Counter

import corpus_pipeline
from laneforge.llm import bpe, mixing
from tests.llm.test_language import Plain as Language
from tests.llm.test_passages import plain_passages
from tests.llm.test_shingles import plain_near

GERMAN = "der Hund und die Katze sind nicht auf dem Tisch, aber das ist auch gut so und wird nicht anders "
EXTRA = [
    (900_001, None, "en", "src1", 0),
    (900_002, "", None, None, 0),
    (900_003, "123 !!", "en", "src2", 6),
    (900_004, "one line\ntwo lines here\nthree lines there\nfour", "en", "src3", 40),
    (900_005, "one line\ntwo lines here\nthree lines there\nfour", "en", "src3", 40),
    (900_006, GERMAN * 3, None, "src4", 300),
    (900_007, "own start\none line\ntwo lines here\nown end", None, "src5", 40),
]


def plain_pipeline(rows):
    import duckdb
    import pandas as pd
    import public_tokenizers
    import tiktoken

    model, known = Language([(r[2], r[1]) for r in rows]), []
    for r in rows:
        lang, score = model.predict(r[1])
        if lang != "und" and score >= 0.3:
            known.append((r[0], r[1], r[2] or lang, *r[3:]))
    lines = plain_passages([(r[0], r[1]) for r in known])
    rows = [(r[0], "\n".join(lines[r[0]]), *r[2:]) for r in known if "\n".join(lines[r[0]])]
    rows = [r for r, least in zip(rows, plain_near([(r[0], r[1]) for r in rows])) if r[0] == least]
    con = duckdb.connect()
    con.register("frame", pd.DataFrame(rows, columns=["doc_id", "text", "lang", "source", "n_chars"]).astype({"lang": object, "source": object}))
    con.sql("CREATE VIEW documents AS SELECT * FROM frame")
    copies = {r[0]: r[-1] for r in con.sql(f"SELECT doc_id, copies FROM ({mixing.ORACLE})").fetchall()}
    ranks = bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    real = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    out = Counter()
    for r in rows:
        if copies[r[0]]:
            out[(*r, tuple(real.encode_ordinary(r[1])))] += copies[r[0]]
    return out


def test_pipeline(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"]) for r in docs.collect()] + EXTRA
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    frame.write.parquet(f"{tmp_path}/documents.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path))
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "token_ids"]
    got = Counter((r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"], tuple(r["token_ids"])) for r in out.collect())
    assert got == plain_pipeline(rows)


def test_stages_keep_the_columns(spark):
    frame = spark.createDataFrame([(1, "some words\nmore words", "en", "src1", 21, "z", 3, 4)], "doc_id long, text string, lang string, source string, n_chars long, row string, n_removed int, `a b-c` int")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, frame, "").columns == frame.columns
        assert stage(spark, frame.limit(0), "").count() == 0
