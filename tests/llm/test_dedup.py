"""Exact, near and line deduplication against plain versions."""

import hashlib
from collections import Counter, defaultdict

import numpy as np
import xxhash

from laneforge.llm import exact_dedup, line_dedup, simhash

SCHEMA = "doc_id long, text string, n_removed string, fp string, row string, id string"
UP = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def edge_rows():
    """Nulls, empty and long texts, ties, repeated rows, and extra columns whose names clash."""
    texts = [None, "", "  ", "Hello World", "hello world", "hello wörld", "HELLO WÖRLD", "a b c d e f g", "a\nb\nc\nd\ne\nf", "x", "x", "w " * 30000, "line one\nline two\nline three"]
    rows = [(i, t, "n", "f", "r", "i") for i, t in enumerate(texts * 3)]
    rows += [(5, "hello wörld", None, None, None, None), (None, "nobody", None, None, None, None), (None, None, None, None, None, None), (None, "x", None, None, None, None)]
    return rows


def documents(spark, sf):
    return [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]


def test_exact_groups(spark, sf):
    for keep in ("min", "max"):
        rows = [(r[0], r[1]) for r in edge_rows()] + [(i + 1000, t) for i, t in documents(spark, sf)]
        groups = defaultdict(list)
        for i, t in rows:
            groups[(t or "").translate(UP)].append(i)
        want = Counter()
        for text, ids in groups.items():
            known = [i for i in ids if i is not None]
            best = (min if keep == "min" else max)(known) if known else None
            for i in ids:
                want[i, best, len(ids), i == best, hashlib.sha256(text.encode()).hexdigest()] += 1
        frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
        got = Counter(tuple(r) for r in exact_dedup.exact_groups(spark, frame, keep=keep, fan_in=2, rounds=3).collect())
        assert got == want


def test_exact_empty_and_clash(spark):
    assert exact_dedup.exact_groups(spark, spark.createDataFrame([], SCHEMA)).count() == 0
    frame = spark.createDataFrame(edge_rows(), SCHEMA)
    kept = exact_dedup.drop_exact_copies(spark, frame)
    assert kept.columns == frame.columns
    assert len({(r["text"] or "").translate(UP) for r in kept.collect()}) == len({(r[1] or "").translate(UP) for r in edge_rows()})


def plain_fingerprint(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    count = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s, 42)
        for b in range(64):
            count[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * count[b] > len(shingles))


def plain_components(fps):
    names = sorted(set(fps))
    parent = {f: f for f in names}

    def find(f):
        while parent[f] != f:
            parent[f] = parent[parent[f]]
            f = parent[f]
        return f

    a = np.array(names, np.uint64)
    for i, f in enumerate(names):
        near = np.bitwise_count(a[i + 1 :] ^ np.uint64(f)) <= 2
        for g in a[i + 1 :][near].tolist():
            parent[find(f)] = find(g)
    return {f: find(f) for f in names}


def check_near(spark, rows, **options):
    fps = [plain_fingerprint(t) for _, t in rows]
    root = plain_components(fps)
    least = {}
    for (i, _), f in zip(rows, fps):
        if i is not None:
            least[root[f]] = min(least.get(root[f], i), i)
    want = Counter((i, f, least.get(root[f])) for (i, _), f in zip(rows, fps))
    got = simhash.near_groups(spark, spark.createDataFrame(rows, "doc_id long, text string").repartition(3), **options).collect()
    assert Counter((r["id"], r["fp"] & (1 << 64) - 1, r["component_id"]) for r in got) == want


def test_near_groups(spark, sf):
    rows = [(r[0], r[1]) for r in edge_rows()] + [(i + 1000, t) for i, t in documents(spark, sf)]
    check_near(spark, rows)
    check_near(spark, rows, bucket_limit=1)


def test_near_links_of_crowded_buckets(spark):
    rng = np.random.default_rng(3)
    fps = {0}
    for base in rng.integers(0, 2**63, 4).tolist():
        at = base
        for _ in range(150):
            fps.add(at)
            at ^= 1 << int(rng.integers(64))
            if rng.random() < 0.3:
                at ^= 1 << int(rng.integers(64))
                at ^= 1 << int(rng.integers(64))
    root = plain_components(fps)
    frame = spark.createDataFrame([(int(np.uint64(f).astype(np.int64)),) for f in fps], "fp long")
    for limit in (4, 10_000):
        nodes = {r["node"] & (1 << 64) - 1: r["root"] & (1 << 64) - 1 for r in simhash.components(spark, simhash.near_links(spark, frame, limit)).collect()}
        groups = defaultdict(set)
        for f in fps:
            groups[root[f]].add(nodes.get(f, f))
        assert all(len(g) == 1 for g in groups.values())
        assert len({next(iter(g)) for g in groups.values()}) == len(groups)


def test_near_drop(spark):
    frame = spark.createDataFrame(edge_rows(), SCHEMA)
    kept = simhash.drop_near_copies(spark, frame)
    assert kept.columns == frame.columns
    assert Counter(r["text"] for r in kept.collect() if r["text"] and r["text"].startswith("a b"))["a b c d e f g"] == 1
    assert simhash.near_groups(spark, spark.createDataFrame([], SCHEMA)).count() == 0


def plain_lines(rows):
    chunks, first = {}, {}
    for key, text in rows:
        lines = (text or "").encode().split(b"\n") if text else []
        chunks[key] = [b"\n".join(lines[a:b]) for a, b in line_dedup.cut_lines(lines)]
        for k, (c, (a, b)) in enumerate(zip(chunks[key], line_dedup.cut_lines(lines))):
            if b - a > 1:
                first[c] = min(first.get(c, (key, k)), (key, k))
    out = {}
    for key, text in rows:
        gone = [k for k, c in enumerate(chunks[key]) if c in first and first[c] < (key, k) and b"\n" in c]
        out[key] = (len(chunks[key]), len(gone), b"\n".join(c for k, c in enumerate(chunks[key]) if k not in gone).decode() if gone else text)
    return out


def test_line_dedup(spark, sf):
    rows = documents(spark, sf)
    shared = "\n".join(f"shared line {i} of a long licence text" for i in range(20))
    rows += [(10_000 + i, f"own start {i}\nown second {i}\n" + shared + f"\nown end {i}") for i in range(30)]
    want = plain_lines(rows)
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: (r["n_chunks"], r["n_removed"], r["text"]) for r in line_dedup.drop_repeated_chunks(spark, frame).collect()}
    assert got == want
    assert sum(shared[200:600] in (t or "") for _, _, t in got.values()) == 1


def test_line_edges(spark):
    frame = spark.createDataFrame(edge_rows(), SCHEMA)
    out = line_dedup.drop_repeated_chunks(spark, frame)
    assert out.columns == ["doc_id", "text", "fp", "row", "id", "n_chunks", "n_removed"]
    got = out.collect()
    assert len(got) == len(edge_rows())
    assert sum(r["text"] is None for r in got) == 4
    assert line_dedup.line_stage(spark, frame).columns == frame.columns
    assert line_dedup.drop_repeated_chunks(spark, spark.createDataFrame([], SCHEMA)).count() == 0


def test_cuts_resist_shifts():
    lines = [b"line %d" % (i * i % 977) for i in range(300)]
    whole = {tuple(lines[a:b]) for a, b in line_dedup.cut_lines(lines)}
    moved = [b"new"] + lines
    again = {tuple(moved[a:b]) for a, b in line_dedup.cut_lines(moved)}
    assert len(whole & again) >= 0.9 * len(whole)
    assert all(b - a >= 2 for a, b in line_dedup.cut_lines(lines))
