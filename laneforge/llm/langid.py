"""Language identification: script ranges narrow the candidates, Viterbi labels the words.

The model is a table of 2^16 hashed windows of up to four bytes within a word, counted for each language over all
labelled training texts; its size does not depend on the corpus. A word's score for a language is the sum of the log
probabilities of its windows. A word in a script that only some of the languages use is a word of those. Within a
text, the path of labels maximises the scores minus a penalty for each switch; runs of one label are the spans.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_part, freed
from .words import SPACE, pieces, word_spans

BUCKETS = 1 << 16
#: Bytes of text that the recursion goes through together.
TOGETHER = 1 << 21
#: Fixed value: the language of a text that is null or has no letter.
UNKNOWN = "und"
#: First and last code points of letters of a script, by script (Unicode blocks).
SCRIPTS = [
    ("latin", 0x00C0, 0x024F), ("latin", 0x1E00, 0x1EFF), ("greek", 0x0370, 0x03FF), ("greek", 0x1F00, 0x1FFF),
    ("cyrillic", 0x0400, 0x052F), ("armenian", 0x0531, 0x0587), ("hebrew", 0x05D0, 0x05F2), ("arabic", 0x0620, 0x06FF),
    ("arabic", 0x0750, 0x077F), ("devanagari", 0x0900, 0x097F), ("bengali", 0x0980, 0x09FF), ("gurmukhi", 0x0A00, 0x0A7F),
    ("gujarati", 0x0A80, 0x0AFF), ("tamil", 0x0B80, 0x0BFF), ("telugu", 0x0C00, 0x0C7F), ("kannada", 0x0C80, 0x0CFF),
    ("malayalam", 0x0D00, 0x0D7F), ("thai", 0x0E00, 0x0E7F), ("lao", 0x0E80, 0x0EFF), ("tibetan", 0x0F00, 0x0FFF),
    ("myanmar", 0x1000, 0x109F), ("georgian", 0x10A0, 0x10FF), ("hangul", 0x1100, 0x11FF), ("ethiopic", 0x1200, 0x137F),
    ("khmer", 0x1780, 0x17FF), ("kana", 0x3041, 0x30FF), ("han", 0x3400, 0x4DBF), ("han", 0x4E00, 0x9FFF),
    ("hangul", 0xAC00, 0xD7A3), ("han", 0x20000, 0x2FA1F),
]
NAMES = list(dict.fromkeys(name for name, _, _ in SCRIPTS))
_FIRST = np.array(sorted(a for _, a, _ in SCRIPTS))
_LAST = np.array([b for _, _, b in sorted(SCRIPTS, key=lambda s: s[1])])
_SCRIPT = np.array([NAMES.index(n) for n, _, _ in sorted(SCRIPTS, key=lambda s: s[1])])
_LETTER = np.zeros(256, bool)
_LETTER[0x61:0x7B] = True  # A-Z come lower-cased


def _windows(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """For each byte, the bucket of the window that ends there; BUCKETS for white space. No window goes beyond its word or its text."""
    space, fresh = SPACE[data], np.zeros(len(data) + 1, bool)
    fresh[offsets] = True
    total = data.astype(np.uint32)
    alive = np.ones(len(data), bool)
    for back in (1, 2, 3):
        if len(data) <= back:
            break
        alive[back:] &= ~space[:-back] & ~fresh[1 : len(data) - back + 1]
        alive[:back] = False
        total[back:] |= np.where(alive[back:], data[:-back].astype(np.uint32) << np.uint32(8 * back), 0).astype(np.uint32)
    h = (total * np.uint32(2654435761)) >> np.uint32(16)
    return np.where(space, BUCKETS, h).astype(np.int32)


def _letters(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions and scripts of letters beyond ASCII that a script's range holds."""
    at = np.flatnonzero(data >= 0xC0)
    if not len(at):
        return at, at
    d = np.concatenate([data, np.zeros(3, np.uint8)]).astype(np.int64)
    b, c1, c2, c3 = d[at], d[at + 1] & 63, d[at + 2] & 63, d[at + 3] & 63
    point = np.where(b < 0xE0, (b & 31) << 6 | c1, np.where(b < 0xF0, (b & 15) << 12 | c1 << 6 | c2, (b & 7) << 18 | c1 << 12 | c2 << 6 | c3))
    k = np.searchsorted(_FIRST, point, "right") - 1
    ok = (k >= 0) & (point <= _LAST[k]) & (point != 0xD7) & (point != 0xF7)
    return at[ok], _SCRIPT[k[ok]]


def _count(langs: list[str]):
    """Counts windows and scripts of the labelled texts of a partition; rows (lang number, bucket, n)."""
    number = {x: i for i, x in enumerate(langs)}

    @freed
    def run(batches):
        windows, scripts = np.zeros((len(langs), BUCKETS + 1), np.int64), np.zeros((len(langs), len(NAMES)), np.int64)
        for batch in batches:
            label = np.array([number[x] for x in batch.column(0).to_pylist()], np.int64)
            for at, offsets, data in pieces(batch.column(1)):
                of = np.repeat(label[at : at + len(offsets) - 1], np.diff(offsets))
                windows += np.bincount(of * (BUCKETS + 1) + _windows(data, offsets), minlength=windows.size).reshape(windows.shape)
                place, kind = _letters(data)
                scripts += np.bincount(of[place] * len(NAMES) + kind, minlength=scripts.size).reshape(scripts.shape)
                scripts[:, 0] += np.bincount(of[_LETTER[data]], minlength=len(langs))
        for i in range(len(langs)):
            for offset, counts in ((0, windows[i, :BUCKETS]), (BUCKETS, scripts[i])):
                k = np.flatnonzero(counts)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), i, np.int32)), pa.array((k + offset).astype(np.int32)), pa.array(counts[k])], ["lang", "bucket", "n"])

    return run


class Model:
    def __init__(self, langs: list[str], windows: np.ndarray, scripts: np.ndarray, smoothing: float = 0.5):
        self.langs = langs
        total = windows.sum(axis=1, keepdims=True)
        table = np.log((windows + smoothing) / (total + smoothing * BUCKETS))
        table = table - table.max(axis=0, keepdims=True) if len(langs) else table
        self.table = np.concatenate([table, np.zeros((len(langs), 1))], axis=1).astype(np.float32)
        share = scripts / np.maximum(scripts.sum(axis=1, keepdims=True), 1)
        self.uses = share >= 0.01  # scripts of a language
        self.uses[:, ~self.uses.any(axis=0)] = True  # a script that none uses excludes none

    def scores(self, data, offsets, starts):
        """Score of each word for each language, and whether it has letters."""
        buckets = _windows(data, offsets)
        out = np.stack([np.add.reduceat(t[buckets], starts) for t in self.table], axis=1).astype(np.float64)
        ascii_letters = np.add.reduceat(_LETTER[data].astype(np.int64), starts) > 0
        place, kind = _letters(data)
        word = np.searchsorted(starts, place, "right") - 1
        script = np.where(ascii_letters, 0, -1)
        script[word] = np.where(script[word] > 0, script[word], np.maximum(kind, script[word]))
        known = script >= 0
        out[~known] = 0.0
        out[known] += np.where(self.uses[:, script[known]].T, 0.0, -1e4)
        return out, known


def train(spark: SparkSession, labelled: DataFrame, lang_col: str = "lang", text_col: str = "text") -> Model:
    """Learns from all rows with a language and a text. The driver gets one number for each language and bucket at most."""
    rows = labelled.select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text")).dropna()
    langs = sorted(r[0] for r in rows.select("lang").distinct().collect())  # as many as there are languages
    windows, scripts = np.zeros((len(langs), BUCKETS)), np.zeros((len(langs), len(NAMES)))
    if langs:
        found = rows.mapInArrow(_count(langs), "lang int, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toPandas()
        low = found[found.bucket < BUCKETS]
        windows[low.lang, low.bucket] = low.n
        high = found[found.bucket >= BUCKETS]
        scripts[high.lang, high.bucket - BUCKETS] = high.n
    return Model(langs, windows, scripts)


def viterbi(scores: np.ndarray, lens: np.ndarray, penalty: float) -> np.ndarray:
    """The best label of every word of texts laid end to end; lens has their numbers of words.

    A text stays with its best single label if no other label gains more than half the penalty over any run of
    words: every span of another label then costs more in switches than it gains. Only the rest need the recursion,
    which advances all texts of about one length together.
    """
    n, k = scores.shape
    labels = np.zeros(n, np.int64)
    full = np.flatnonzero(lens > 0)
    if not len(full) or k < 2:
        return labels
    size = lens[full]
    first = np.cumsum(size) - size
    text = np.repeat(np.arange(len(full)), size)
    best = np.add.reduceat(scores, first, axis=0).argmax(axis=1)
    labels[:] = best[text]
    own = scores[np.arange(n), labels]
    gain = np.zeros(len(full))
    for j in range(k):
        run = np.cumsum(scores[:, j] - own)
        run -= np.concatenate([[0.0], run])[first][text]
        span = float(np.abs(run).max()) * 2 + 1
        low = np.minimum.accumulate(np.concatenate([[0.0], run[:-1]]) * (np.r_[False, text[1:] == text[:-1]]) - text * span) + text * span
        gain = np.maximum(gain, np.maximum.reduceat(run - np.minimum(low, 0.0), first))
    mixed = np.flatnonzero(gain > penalty / 2)
    mixed = mixed[np.argsort(-size[mixed], kind="stable")]
    at = 0
    while at < len(mixed):
        longest = int(size[mixed[at]])
        group = mixed[at : at + max(1, 4_000_000 // (longest * k))]
        group = group[size[group] * 2 >= longest]
        at += len(group)
        begin, length = first[group], size[group]
        alive = np.searchsorted(-length, -np.arange(longest), "left")  # texts with a word at each step
        v = scores[begin].copy()
        back = np.zeros((longest, len(group), k), np.int8 if k < 128 else np.int32)
        for t in range(1, longest):
            m = alive[t]
            top = v[:m].argmax(axis=1)
            change = v[np.arange(m), top] - penalty
            stay = v[:m] >= change[:, None]
            back[t, :m] = np.where(stay, np.arange(k), top[:, None])
            v[:m] = np.where(stay, v[:m], change[:, None]) + scores[begin[:m] + t]
        now = v.argmax(axis=1)
        for t in range(longest - 1, -1, -1):
            m = alive[t]
            labels[begin[:m] + t] = now[:m]
            now[:m] = back[t, np.arange(m), now[:m]]
    return labels


def _has_letter(text: str | None) -> bool:
    return bool(text) and any(map(str.isalpha, text))


def _judged(model: Model, penalty: float, texts: pa.Array, spans: bool = False):
    """Of each text: its language (und: null or without a letter), the winner's share, and the runs of one language."""
    pred, score, found = [], [], []
    for at, offsets, data in pieces(texts, TOGETHER):
        starts, ends, lens = word_spans(offsets, data)
        m, k = len(lens), len(model.langs)
        letters = np.add.reduceat(np.r_[_LETTER[data], False].astype(np.int64), offsets[:-1]) * (np.diff(offsets) > 0) > 0
        for i in np.flatnonzero(~letters):
            letters[i] = _has_letter(texts[at + int(i)].as_py())
        if k and len(starts):
            s, known = model.scores(data, offsets, starts)
            labels = viterbi(s, lens, penalty)
            weight = np.bincount(np.repeat(np.arange(m), lens) * k + labels, (ends - starts) * known, m * k).reshape(m, k)
        else:
            labels, weight = np.zeros(len(starts), np.int64), np.zeros((m, k))
        if k:
            top = weight.argmax(axis=1)
            share = np.where(letters, weight[np.arange(m), top] / np.maximum(weight.sum(axis=1), 1), 0.0)
            pred += [model.langs[t] if ok else UNKNOWN for t, ok in zip(top, letters)]
        else:
            share = np.zeros(m)
            pred += [UNKNOWN] * m
        score.append(share)
        if spans:
            first = 0
            for n in lens.tolist():
                own = labels[first : first + n]
                edge = np.r_[0, np.flatnonzero(np.diff(own)) + 1, n] if n and k else np.zeros(1, int)
                found.append([{"first": int(a), "last": int(b), "lang": model.langs[own[a]]} for a, b in zip(edge[:-1], edge[1:])])
                first += n
    return pred, np.concatenate(score) if score else np.zeros(0), found


def _predict(model: Model, penalty: float, spans: bool):
    @freed
    def run(batches):
        for batch in batches:
            pred, score, found = _judged(model, penalty, batch.column(2), spans)
            columns = [batch.column(0), batch.column(1), pa.array(pred, pa.string()), pa.array(score, pa.float64())]
            names = ["id", "held_out", "lang_pred", "score"]
            if spans:
                columns.append(pa.array(found, pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32()), ("lang", pa.string())]))))
                names.append("spans")
            yield pa.RecordBatch.from_arrays(columns, names)

    return run


def _settle(model: Model, penalty: float, least: float, lang: int, text: int):
    """Keeps the rows whose text is in some language; a row without a language gets the predicted one."""

    @freed
    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):  # some rows at a time: a batch may hold many long texts
                part = batch.slice(at, 2048)
                texts = part.column(text)
                if model.langs:
                    pred, score, _ = _judged(model, penalty, texts)
                    keep = [p != UNKNOWN and s >= least for p, s in zip(pred, score.tolist())]
                else:  # nothing to judge by: letters decide
                    pred, keep = [None] * part.num_rows, [_has_letter(x.as_py()) for x in texts]
                named = pc.fill_null(part.column(lang), pa.array([p if k else None for p, k in zip(pred, keep)], pa.string()))
                yield part.set_column(lang, part.schema.field(lang), named).filter(pa.array(keep, pa.bool_()))

    return run


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", held=None, penalty: float = 14.0, spans: bool = False) -> DataFrame:
    """id, held_out, lang_pred, score for every whole text, and with spans=True the runs of words of one language.

    score: the share of the winner in the bytes of lettered words. A text that is null or has no letter is `und` with
    score 0 (all are, where nothing could be learnt). Ties go to the language that sorts first. A text of any length is
    read whole; rows that repeat are each judged. Other columns are not read; an empty table gives no rows.
    """
    schema = "id long, held_out boolean, lang_pred string, score double" + (", spans array<struct<first:int,last:int,lang:string>>" if spans else "")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), (F.lit(False) if held is None else held).alias("held_out"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_predict(model, penalty, spans), schema)


def predictions(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Learns from three quarters of the documents, by crc32 of the id, and predicts all."""
    held = crc_part("doc_id", 4) == 2
    return identify(docs, train(spark, docs.filter(~held)), held=held)


def drop_unknown(spark: SparkSession, docs: DataFrame, lang_col: str = "lang", text_col: str = "text", penalty: float = 14.0, least: float = 0.3) -> DataFrame:
    """The documents whose text is in some language, with all their columns; where lang is null, it is the predicted one.

    The model learns from all rows that have a language. Rejected are texts that are null, empty or without a letter,
    and those in which no language has a share of `least` of the lettered words. Where no row has a language there is
    no model and only texts without a letter go. Repeated rows are each judged; an empty table gives no rows; the names
    of other columns never matter.
    """
    model = train(spark, docs, lang_col, text_col)
    rows = docs.withColumns({lang_col: F.col(lang_col).cast("string"), text_col: F.col(text_col).cast("string")})
    return rows.mapInArrow(_settle(model, penalty, least, docs.columns.index(lang_col), docs.columns.index(text_col)), rows.schema)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return predictions(spark, spark.read.parquet(f"{sf_dir}/documents.parquet")).withColumnRenamed("id", "doc_id")
