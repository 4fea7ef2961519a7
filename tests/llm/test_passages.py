"""Repeated passages of lines: recall on planted ones, and against a plain version."""

import random

from laneforge.llm import line_dedup


def plain_passages(rows):
    """The lines that stay of each text."""
    first, out = {}, {}
    texts = {key: text.split("\n") for key, text in rows}
    for key in sorted(texts):
        for i in range(len(texts[key]) - 1):
            first.setdefault(tuple(texts[key][i : i + 2]), (key, i))
    for key, lines in texts.items():
        gone = set()
        for i in range(len(lines) - 1):
            at = first[tuple(lines[i : i + 2])]
            if at < (key, i) and (at[0] != key or i >= at[1] + 2) and any(x.strip() for x in lines[i : i + 2]):
                gone |= {i, i + 1}
        out[key] = [x for i, x in enumerate(lines) if i not in gone]
    return out


def test_planted_passages_go_whole(spark):
    """A passage of 2 to 10 lines that two documents share, between lines of their own, stays once and whole."""
    rng, rows, planted = random.Random(7), [], []
    for n in range(2, 11):
        for k in range(20):
            passage = [f"passage {n} {k} line {i}" for i in range(n)]
            for _ in range(2):
                key = len(rows)
                own = [f"own {key} {i}" for i in range(rng.randint(2, 12))]
                at = rng.randint(0, len(own))
                rows.append((key, "\n".join(own[:at] + passage + own[at:])))
                planted.append((key, own, passage))
    got = {r["doc_id"]: r for r in line_dedup.drop_repeated_passages(spark, spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()}
    for key, own, passage in planted:
        lines = got[key]["text"].split("\n")
        if key % 2:
            assert lines == own and got[key]["n_removed"] == 1
        else:
            assert got[key]["text"] == rows[key][1] and (got[key]["n_chunks"], got[key]["n_removed"]) == (1, 0)


def test_passages_of_documents(spark, sf):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").filter("text IS NOT NULL").collect()]
    rows += [(10**6, "x\nx\nx\nx\nx"), (10**6 + 1, "a\n\n\n\nb"), (10**6 + 2, "c\n\n\n\nd"), (10**6 + 3, "q\na\nb\nc"), (10**6 + 4, "a\nb\nz"), (10**6 + 5, "b\nz")]
    got = {r["doc_id"]: r["text"] for r in line_dedup.drop_repeated_passages(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {key: "\n".join(lines) for key, lines in plain_passages(rows).items()}
    assert {x for _, t in rows for x in t.split("\n")} == {x for t in got.values() for x in t.split("\n")} | {x for x in [""] if any("" in t.split("\n") for _, t in rows)}
    assert got[10**6] == "x\nx"
