"""Language identification against a plain scorer of one text after the other."""

import math
import zlib
from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from laneforge.llm import langid
from laneforge.llm.common import crc_part


def words(text):
    return (text or "").encode().lower().split()


def buckets(word):
    """The 2^16 buckets of the windows of up to four bytes that end at each byte, the latest byte lowest."""
    out = []
    for i in range(len(word)):
        window = word[max(0, i - 3) : i + 1][::-1]
        out.append(int.from_bytes(window, "little") * 2654435761 % 2**32 >> 16)
    return out


def scripts(word):
    """Scripts of the word's letters: latin for a-z, and those whose ranges hold a letter."""
    out = set()
    for c in word.decode():
        if "a" <= c <= "z":
            out.add("latin")
        for name, first, last in langid.SCRIPTS:
            if first <= ord(c) <= last and c not in "×÷":
                out.add(name)
    return out


def letters_by_script(text):
    out = defaultdict(int)
    for c in (text or "").encode().lower().decode():
        for name, first, last in [("latin", 0x61, 0x7A), *langid.SCRIPTS]:
            if first <= ord(c) <= last and c not in "×÷":
                out[name] += 1
    return out


class Plain:
    def __init__(self, rows):
        """rows: (lang, text)."""
        rows = [(lang, t) for lang, t in rows if lang is not None and t is not None]
        self.langs = sorted({lang for lang, _ in rows})
        self.counts = {lang: defaultdict(int) for lang in self.langs}
        letters = {lang: defaultdict(int) for lang in self.langs}
        for lang, text in rows:
            for w in words(text):
                for b in buckets(w):
                    self.counts[lang][b] += 1
            for s, n in letters_by_script(text).items():
                letters[lang][s] += n
        self.total = {lang: sum(c.values()) for lang, c in self.counts.items()}
        self.uses = {lang: {s for s, n in letters[lang].items() if n >= 0.01 * sum(letters[lang].values())} for lang in self.langs}

    def score(self, word):
        found = scripts(word)
        script = max(found, key=langid.NAMES.index) if found else None
        out = []
        for lang in self.langs:
            s = sum(math.log((self.counts[lang][b] + 0.5) / (self.total[lang] + 0.5 * 65536)) for b in buckets(word))
            if script and any(script in u for u in self.uses.values()) and script not in self.uses[lang]:
                s -= 1e4
            out.append(s if found else 0.0)
        return out, bool(found)

    def predict(self, text, penalty=14.0):
        if not text or not any(map(str.isalpha, text)) or not self.langs:
            return "und", 0.0
        scored, n = [(self.score(w), len(w)) for w in words(text)], len(self.langs)
        best, paths = scored[0][0][0], []
        for (s, _), _ in scored[1:]:
            top = max(range(n), key=best.__getitem__)
            paths.append([k if best[k] >= best[top] - penalty else top for k in range(n)])
            best = [max(best[k], best[top] - penalty) + s[k] for k in range(n)]
        label = max(range(n), key=best.__getitem__)
        labels = [label]
        for p in reversed(paths):
            label = p[label]
            labels.append(label)
        weight = [0] * n
        for k, ((_, known), size) in zip(reversed(labels), scored):
            weight[k] += size * known
        top = max(range(n), key=weight.__getitem__)
        return self.langs[top], weight[top] / max(1, sum(weight))


def test_predictions(spark, sf):
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang", "text").filter("n_chars < 6000").collect()]
    by = {lang: [t for _, x, t in rows if x == lang] for lang in {x for _, x, _ in rows}}
    rows += [(900_000 + i, None, by["en"][i][:400] + " " + by["de"][i][:300] + " " + by["fr"][i][:500]) for i in range(6)]
    rows += [(910_000, "ru", "привет мир это текст " * 5), (910_001, None, "ещё один текст и слова"), (910_002, None, None), (910_003, "en", ""), (910_004, "en", "12 !!"), (910_005, None, "漢字"), (910_006, None, "x"), (910_006, None, "x"), (None, "en", "the words of a text")]
    frame = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, lang string, text string, lang_pred string").repartition(4)
    plain = Plain([(lang, t) for i, lang, t in rows if zlib.crc32(("" if i is None else str(i)).encode()) % 4 != 2])
    held = crc_part("doc_id", 4) == 2
    got = langid.identify(frame, langid.train(spark, frame.filter(~held)), held=held).collect()
    want = defaultdict(list)
    for i, _, t in rows:
        want[i].append(plain.predict(t))
    assert len(got) == len(rows)
    for r in got:
        assert (r["lang_pred"], pytest.approx(r["score"], abs=1e-6)) == want[r["id"]][0], r["id"]
        assert r["held_out"] == (zlib.crc32(("" if r["id"] is None else str(r["id"])).encode()) % 4 == 2)


def test_stage_keeps_and_names(spark, sf):
    """The pipeline's stage: null languages are predicted, texts without a letter go, and a corpus without languages stays."""
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang").limit(80).collect()]
    hidden = [(i, t, None if k % 5 == 0 else lang) for k, (i, t, lang) in enumerate(rows)] + [(-1, None, "en"), (-2, "", "en"), (-3, "77 --", None)]
    frame = spark.createDataFrame([(*r, 1) for r in hidden], "doc_id long, text string, lang string, `held out` int").repartition(3)
    plain = Plain([(lang, t) for _, t, lang in hidden])
    out = langid.drop_unknown(spark, frame)
    assert out.columns == frame.columns
    want = {}
    for i, t, lang in hidden:
        pred, score = plain.predict(t)
        if pred != "und" and score >= 0.3:
            want[i] = (t, lang or pred)
    assert {r["doc_id"]: (r["text"], r["lang"]) for r in out.collect()} == want and len(want) == len(rows)
    unnamed = spark.createDataFrame([(1, "two words", None), (2, "12", None), (3, None, None), (4, "слово", None)], "doc_id long, text string, lang string")
    assert sorted(r["doc_id"] for r in langid.drop_unknown(spark, unnamed).collect()) == [1, 4]
    assert langid.drop_unknown(spark, unnamed.limit(0)).count() == 0


def test_windows_end_at_texts(spark):
    """What a text is scored by does not hang on the texts around it."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").filter("n_chars < 300")
    model = langid.train(spark, docs)
    one = {r["id"]: (r["lang_pred"], r["score"]) for r in langid.identify(docs.coalesce(1).orderBy("doc_id"), model).collect()}
    assert one == {r["id"]: (r["lang_pred"], r["score"]) for r in langid.identify(docs.repartition(7, F.rand(1)), model).collect()}
