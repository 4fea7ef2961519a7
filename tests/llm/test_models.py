"""Language identification, language model, tokenizer, search, rules and mixing against plain versions."""

import random
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from laneforge.llm import bpe, imi, langid, mixing, pii, url_rules

PUBLIC = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
EDGES = [(None, None), (900001, ""), (900002, " \t\n"), (900003, "Zzyzx unseen wörds"), (900003, "Zzyzx unseen wörds"), (900004, "12 34 !!"), (900005, "word " * 20000)]


def documents(spark, sf):
    return [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]


def test_language_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.predictions(spark, docs).join(docs.select(F.col("doc_id").alias("id"), "lang"), "id").filter("held_out").collect()
    assert len(got) > 150
    assert sum(r["lang_pred"] == r["lang"] for r in got) >= 0.97 * len(got)
    assert all(0 <= r["score"] <= 1 for r in got)


def test_language_spans_and_edges(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.train(spark, docs)
    first = {r["lang"]: " ".join(r["text"].split()[:60]) for r in docs.filter("n_chars > 2000").collect()}
    rows = [*EDGES, (1, first["en"] + " " + first["de"]), (2, "привет мир"), (3, "漢字")]
    got = {r["id"]: r for r in langid.identify(spark.createDataFrame(rows, "doc_id long, text string"), model, spans=True).collect()}
    assert [got[i]["lang_pred"] for i in (None, 900001, 900002, 900004)] == ["und"] * 4
    spans = got[1]["spans"]
    assert [s["lang"] for s in spans] == ["en", "de"] and abs(spans[0]["last"] - 60) <= 3
    assert got[2]["lang_pred"] in model.langs
    empty = langid.train(spark, docs.limit(0))
    assert {r["lang_pred"] for r in langid.identify(spark.createDataFrame(rows, "doc_id long, text string"), empty).collect()} == {"und"}
    assert langid.identify(docs.limit(0), model).count() == 0


def test_viterbi_is_the_best_path():
    rng = np.random.default_rng(1)
    for _ in range(200):
        k, lens = int(rng.integers(1, 5)), rng.integers(0, 9, 6)
        s = np.round(rng.normal(size=(int(lens.sum()), k)) * rng.choice([0.5, 3]), 2)
        got, at, pen = langid.viterbi(s, lens, 2.0), 0, 2.0
        for n in lens:
            value = lambda path, o=at: sum(s[o + i, x] for i, x in enumerate(path)) - pen * sum(a != b for a, b in zip(path, path[1:]))
            v = s[at : at + n]
            if n:
                best = v[0].copy()
                for row in v[1:]:
                    best = np.maximum(best, best.max() - pen) + row
                assert value(got[at : at + n].tolist()) == pytest.approx(best.max())
            at += int(n)


def test_bpe_equals_reference(spark, sf):
    import tiktoken

    path, pattern = PUBLIC
    c = bpe.Codec(bpe.read_ranks(path), pattern)
    real = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=c.ranks, special_tokens={})
    rng = random.Random(1)
    alphabet = "ab'stré \t\n\r\x0b\x0c\x1c\x1f\x85\xa0　﻿中ab١²½ǅ😀́\x00!!-_01<|endoftext|> "
    texts = [t or "" for _, t in documents(spark, sf)[:60] + EDGES] + ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 50))) for _ in range(500)]
    for t in texts:
        ids = c.encode(t)
        assert ids == real.encode_ordinary(t)
        assert c.decode(ids) == t.encode()


def test_bpe_digests(spark, sf):
    import hashlib

    path, pattern = PUBLIC
    c = bpe.Codec(bpe.read_ranks(path), pattern)
    rows = documents(spark, sf)[:40] + EDGES
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    want = Counter()
    for i, t in rows:
        ids = c.encode(t or "")
        want[i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    assert Counter(tuple(r) for r in bpe.encoding_digests(frame.withColumn("n_tokens", F.lit("clash"))).collect()) == want
    assert bpe.encoding_digests(frame.limit(0)).count() == 0
    back = bpe.decode_ids(bpe.encode_ids(frame.withColumn("token_ids", F.lit("clash")))).collect()
    assert all(bytes(r["decoded"]) == (r["text"] or "").encode() for r in back)
    assert bpe.encode_ids(frame.limit(0)).count() == 0


def test_multi_index_recall(spark):
    table = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = [(r["vec_id"], np.array(r["embedding"], float)) for r in table.collect()]
    got = defaultdict(list)
    for r in imi.search(spark, table, table.filter("vec_id % 20 = 0")).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    ids, v = np.array([i for i, _ in rows]), np.stack([x for _, x in rows])
    hit = n = 0
    for i, q in rows:
        if i % 20 == 0:
            s = (v * q).sum(axis=1)
            order = np.lexsort((ids, -s))
            best = [int(x) for x in ids[order] if x != i][:20]
            own = sorted(got[i])
            assert [r for r, _, _ in own] == list(range(1, 21))
            assert [(-s, x) for _, x, s in own] == sorted((-s, x) for _, x, s in own)
            hit, n = hit + len(set(best) & {x for _, x, _ in own}), n + 20
    assert hit >= 0.9 * n


def test_multi_index_ties_and_edges(spark):
    rows = [(i, [1.0, 0.0, 0.5, 0.25]) for i in range(300)] + [(300 + i, [float(i % 7), 1.0, -1.0, 0.5]) for i in range(50)]
    rows += [(1000, None), (1001, [0.0] * 4), (1002, [float("nan"), 1.0, 1.0, 1.0]), (1003, [None, 1.0, 1.0, 1.0]), (1004, [1.0]), (None, [1.0] * 4), (20, [1.0, 0.0, 0.5, 0.25])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("cell", F.lit("clash"))
    good = [(i, np.array(v)) for i, v in dict((i, v) for i, v in rows if i is not None and i < 1000).items()]
    got = defaultdict(list)
    for r in imi.search(spark, frame, frame.filter("vec_id % 20 = 0"), share=1.0).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"]))
    for i, q in good:
        if i % 20 == 0:
            assert [x for _, x in sorted(got[i])] == [x for _, x in sorted((-float((v * q).sum()), j) for j, v in good if j != i)[:20]]
    assert not set(got) - {i for i, _ in good}
    assert imi.search(spark, frame.limit(0), frame.limit(0)).count() == 0


def test_traverse_is_in_order():
    rng = np.random.default_rng(5)
    a, b, q = rng.normal(size=(6, 3)), rng.normal(size=(5, 3)), rng.normal(size=6)
    sizes = {i: 1 for i in range(30) if i % 4}
    cost = {i * 5 + j: -(a[i] @ q[:3]) - (b[j] @ q[3:]) for i in range(6) for j in range(5)}
    got = imi.traverse(q, a, b, sizes, 100)
    assert got == sorted(sizes, key=cost.get)
    assert imi.traverse(q, a, b, sizes, 4) == got[:4]


def test_url_rules(spark):
    urls = ["http://a.NET/x", "https://www.example.net/en/1?q", "http://example.net/de/", "http://x.example.com/de/1#t", "http://example.com/en", "http://b.org/fr/", "http://net", "http://notnet/x", None, "no scheme", "ftp://", "HTTP://Org/fr/é"]
    rows = [(i, u, "x", "y") for i, u in enumerate(urls * 2)]
    pages = spark.createDataFrame(rows, "page_id long, url string, rule string, items string")
    labels = spark.createDataFrame([(0, 1, 0), (2, 0, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    got = {r["page_id"]: r for r in url_rules.judge(spark, pages, labels).collect()}
    assert len(got) == len(rows)
    assert [(got[i]["host"], got[i]["path"], got[i]["rule"]) for i in range(12)] == [
        ("a.net", "/x", "net/"), ("www.example.net", "/en/1", "example.net/en/"), ("example.net", "/de/", "net/"), ("x.example.com", "/de/1", "example.com/de/"),
        ("example.com", "/en", None), ("b.org", "/fr/", "org/fr/"), ("net", "", None), ("notnet", "/x", None), ("", "", None), ("", "", None), ("", "", None), ("org", "/fr/é", "org/fr/"),
    ]
    assert got[0]["verdict"] == "block" and got[1]["verdict"] == "allow"
    assert {r["verdict"] for r in got.values()} <= {"block", "allow"}
    assert url_rules.judge(spark, pages.limit(0), labels.limit(0)).count() == 0


def plain_rules(rows, need, confidence, longest=3):
    """All rules of up to `longest` tokens that no shorter one makes needless: {(tokens, verdict): (confidence, support)}."""
    from itertools import combinations

    whole, by = Counter(), Counter()
    for items, verdict in rows:
        for k in range(1, longest + 1):
            for s in combinations(sorted(set(items)), k):
                whole[s] += 1
                by[s, verdict] += 1
    want = {(s, v): (n / whole[s], n / len(rows)) for (s, v), n in by.items() if n >= need and n / whole[s] >= confidence}
    return {(s, v): x for (s, v), x in want.items() if not any(want.get((p, v), (0,))[0] >= x[0] for k in range(1, len(s)) for p in combinations(s, k))}


def expanded(rules, classes):
    """Rules over classes of tokens as rules over tokens."""
    from itertools import product

    members = defaultdict(list)
    for r in classes.collect():
        members[r["rep"]].append(r["token"])
    return {(tuple(sorted(s)), r["verdict"]): (pytest.approx(r["confidence"]), pytest.approx(r["support"])) for r in rules.collect() for s in product(*[members[t] for t in r["antecedent"]])}


@pytest.mark.parametrize("wide", [16, 1])
def test_mined_rules(spark, wide):
    """FP-growth, and with wide=1 the growth of bounded length, against counting all sets."""
    good = [["host:a", "path:x"]] * 30 + [["host:a", "path:y"]] * 30
    bad = [["host:b", "host:c", "path:x"]] * 30 + [["host:a", "path:spam", "query:id"]] * 10
    rng = random.Random(5)
    rows = [(i, "allow") for i in good] + [(i, "block") for i in bad]
    rows += [(rng.sample(["t1", "t2", "t3", "t4", "t5", "path:x", "host:a"], rng.randint(1, 6)), rng.choice(["allow", "block", "block"])) for _ in range(60)]
    labelled = spark.createDataFrame([*rows, (["host:a"], None), (None, "allow")], "items array<string>, verdict string")
    rules, classes = url_rules.mine(spark, labelled, 0.03, 0.7, wide=wide)
    want = plain_rules([*rows, ([], "allow")], 5, 0.7)
    assert len(want) > 10 and max(len(s) for s, _ in want) == 3
    assert expanded(rules, classes) == want
    pages = spark.createDataFrame([(1, 1, ["host:c", "zzz"]), (2, 2, ["path:spam", "host:a"]), (3, 3, ["zzz"]), (4, 4, None)], "page_id long, row long, items array<string>")
    got = {r["row"]: r["verdict"] for r in url_rules.judge_by_rules(spark, pages, rules, classes).collect()}
    assert got == {1: "block", 2: "block", 3: "allow", 4: "allow"}


def test_long_urls_end(spark):
    """Urls of 200 tokens: templates that many share, parts at random, and chains of prefixes."""
    import time

    rng = random.Random(6)
    words = [f"w{i}" for i in range(200)]
    rows = [(words, "block")] * 20 + [([f"x{i}" for i in range(200)], "allow")] * 8
    rows += [(words[: rng.choice([40, 60, 80])] + [f"own{i}"], "allow") for i in range(40)]
    rows += [(rng.sample([f"r{i}" for i in range(30)], 25), "allow") for _ in range(40)]
    start = time.time()
    rules, classes = url_rules.mine(spark, spark.createDataFrame(rows, "items array<string>, verdict string"))
    assert rules.count() > 0 and {r["verdict"] for r in rules.collect()} == {"allow", "block"}
    assert time.time() - start < 90


def luhn(d):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d))) % 10 == 0


def plain_pii(text):
    import re

    text, out = text or "", []
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    for kind, pattern in patterns.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            if kind == "email" or kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")) or kind == "card" and 13 <= len(digits) <= 19 and luhn(digits) or kind == "phone" and 9 <= len(digits) <= 15:
                out.append((kind, m.start(), m.end()))
    return out


def test_pii(spark, sf):
    import hashlib

    rng = random.Random(4)
    pieces = ["a.b@c.de", "x@y", "@", "+", "+1 (555) 123-4567", "4111 1111 1111 1111", "4111-1111-1111-1112", "1.2.3.4", "256.1.1.1", "001.2.3.04", "9" * 17, " ", ".", "-", "é", "😀", "a@b.c_d@e.fg", "0", "12", "GB82 WEST 1234 5698 7654 32", "token = \"abcdef0123456789abcd\"", "ssn 123-45-6789", "\n", "%", "5", "1.2.3.4.5.6.7.8"]
    rows = documents(spark, "/root/testdata/sf0.01")[:300] + EDGES
    rows += [(10**6 + i, "".join(rng.choice(pieces) for _ in range(rng.randint(1, 14)))) for i in range(1500)]
    rows += [(2 * 10**6, "1" * 60000), (2 * 10**6 + 1, "a" * 60000 + "@"), (2 * 10**6 + 2, "+1" + " " * 50000), (2 * 10**6 + 3, "a@b" + ".c" * 20000)]
    spark.createDataFrame(rows, "doc_id long, text string").createOrReplaceTempView("pii_docs")
    found = pii.spans(spark.table("pii_docs").withColumn("email", F.lit("clash"))).collect()
    got, want = Counter(), Counter()
    for r in found:
        got[r["id"], tuple((k, s["start"], s["end"]) for k in pii.BASE for s in r[k])] += 1
    for i, t in rows:
        want[i, tuple(plain_pii(t))] += 1
    assert got == want
    extra = spark.createDataFrame([(1, "Konto GB82 WEST 1234 5698 7654 32, GB83 WEST 1234 5698 7654 32"), (2, "ssn: 123-45-6789"), (3, "part 123-45-6789"), (4, 'token = "04dbebab91ab85687d33eeaaf9ac699e1188f962"')], "doc_id long, text string")
    rows = {r["id"]: r for r in pii.spans(extra).collect()}
    assert [(s["start"], s["end"]) for s in rows[1]["iban"]] == [(6, 33)]
    assert len(rows[2]["ssn"]) == 1 and not rows[3]["ssn"] and len(rows[4]["secret"]) == 1
    assert pii.spans(extra.limit(0)).count() == 0
    del hashlib


def test_pii_context_and_many_matches(spark):
    """Words on both sides count, through earlier matches; a text of very many matches ends; positions are exact."""
    many = "".join(f"u{i}@x.org " for i in range(20_000))
    texts = {1: "SSN: 123-45-6789, 234-56-7890", 2: "123-45-6789 (SSN)", 3: "part 123-45-6789 of 234-56-7890", 4: many, 5: "é😀 a@b.cd x@y.zz é 9.9.9.9"}
    frame = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r["id"]: r for r in pii.spans(frame).collect()}
    assert [len(got[i]["ssn"]) for i in (1, 2, 3)] == [2, 1, 0]
    assert [many[s["start"] : s["end"]] for s in got[4]["email"]] == many.split()
    assert [texts[5][s["start"] : s["end"]] for k in ("email", "ip") for s in got[5][k]] == ["a@b.cd", "x@y.zz", "9.9.9.9"]


def test_redact(spark):
    """What is confirmed goes, what fails its check or has no context stays."""
    rows = [(1, "mail a@b.cd, card 4111 1111 1111 1111 not 4111 1111 1111 1112, ip 1.2.3.4 and 300.1.1.1 end"), (2, None), (3, "part 123-45-6789"), (4, "ssn 123-45-6789"), (5, "IBAN DE89370400440532013000 Bitte"), (6, "nothing")]
    out = pii.redact(spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, text string, redacted string"))
    assert out.columns == ["doc_id", "text", "redacted"]
    got = {r["doc_id"]: r["redacted"] for r in out.collect()}
    assert got == {1: "mail [email], card [card] not 4111 1111 1111 1112, ip [ip] and 300.1.1.1 end", 2: "", 3: "part 123-45-6789", 4: "ssn [ssn]", 5: "IBAN [iban] Bitte", 6: "nothing"}
    assert pii.redact(out.limit(0)).count() == 0


def test_mixing_edges(spark):
    rows = [(i, f"text {i}" * (i % 9 + 1), ["en", "de", None][i % 3], ["src1", "src2", "s", None][i % 4], "c") for i in range(400)] + [(5, None, "en", "src1", "c"), (5, None, "en", "src1", "c"), (None, "", None, None, "c")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, domain string")
    mixed = mixing.select_mix(spark, frame, mixing.source_domain()).collect()
    assert len(mixed) == len(rows)
    total = sum(r["_tokens"] for r in mixed)
    budgets = {(r["_domain"], r["lang"], r["source"]): r["_budget"] for r in mixed}
    used = Counter()
    for r in mixed:
        used[r["_domain"], r["lang"], r["source"]] += r["_tokens"] * r["_copies"]
    assert all(used[k] <= b for k, b in budgets.items())
    assert 0.98 * 0.9 * total <= sum(budgets.values()) <= 0.9 * total
    assert max(r["_copies"] for r in mixed) <= mixing.EPOCHS
    assert mixing.select_mix(spark, frame.limit(0), mixing.source_domain()).count() == 0
    assert mixing.mix_stage(spark, frame).columns == frame.columns


def test_budgets_water_fill(spark):
    """Shortage goes to siblings first: source b of (x, en) can't use its half, so source a takes it, not language de."""
    leaves = spark.createDataFrame([("x", "en", "a", 1000), ("x", "en", "b", 10), ("x", "de", "c", 1000), ("y", "en", "d", 50)], "domain string, lang string, source string, capacity long")
    got = {r["source"]: r["budget"] for r in mixing.leaf_budgets(leaves, 400, weights={}).collect()}
    assert got == {"d": 50, "c": 175, "b": 10, "a": 165}
