"""Byte-level BPE through a sentencepiece model that is serialised here from a rank file.

Every byte is one character of a private alphabet, so a vocabulary entry of n bytes is a piece of n characters. Its
score is its negative rank: sentencepiece merges the adjacent pair of highest score, which is the pair of lowest rank.
Normalisation is the identity and white space is neither escaped nor added. Pre-tokens are encoded one by one; an
entry that is itself in the vocabulary is its own code. Decoding maps ids back to the bytes of their entries.
"""

from __future__ import annotations

import base64
import gc
import hashlib
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import freed

#: The character of byte 0; every other byte is the character of its number.
ZERO = "\u0100"
#: Estimated bytes of the pre-tokens that a worker remembers within a task, besides those of the text at hand.
CACHE_BYTES = 64 << 20


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def _varint(n: int) -> bytes:
    out = b""
    while n > 127:
        out += bytes([n & 127 | 128])
        n >>= 7
    return out + bytes([n])


def _field(number: int, payload: bytes) -> bytes:
    return _varint(number << 3 | 2) + _varint(len(payload)) + payload


def _number(number: int, n: int) -> bytes:
    return _varint(number << 3) + _varint(n & (1 << 64) - 1)


def spell(raw: bytes) -> str:
    """Bytes in the private alphabet."""
    return raw.decode("latin-1").replace("\0", ZERO)


def model_proto(ranks: dict[bytes, int]) -> bytes:
    """A serialised sentencepiece model: piece 0 is <unk>, piece rank + 1 is the entry of that rank."""
    import struct

    by_rank = {r: t for t, r in ranks.items()}
    size = max(by_rank, default=-1) + 1
    out = [_field(1, _field(1, b"<unk>") + _varint(2 << 3 | 5) + struct.pack("<f", 0.0) + _number(3, 2))]
    for rank in range(size):
        # A gap in the ranks gets a piece that no text can spell.
        piece = spell(by_rank[rank]) if rank in by_rank else f"<gap {rank}>"
        out.append(_field(1, _field(1, piece.encode()) + _varint(2 << 3 | 5) + struct.pack("<f", float(-rank)) + (b"" if rank in by_rank else _number(3, 5))))
    trainer = _number(3, 2) + _number(4, size + 1) + _number(35, 0) + _number(40, 0) + _number(41, -1) + _number(42, -1) + _number(43, -1)
    normalizer = _field(1, b"identity") + _number(3, 0) + _number(4, 0) + _number(5, 0)
    return b"".join(out) + _field(2, trainer) + _field(3, normalizer)


class Codec:
    """Encodes pre-tokens with a bounded memory of those seen; decodes ids."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import sentencepiece

        self.ranks = ranks
        self.bytes_of = [b""] * (max(ranks.values(), default=-1) + 1)
        for t, r in ranks.items():
            self.bytes_of[r] = t
        #: Decimal ids by piece, which is one more than the rank.
        self.names = ["", *map(str, range(len(self.bytes_of)))]
        self.raw_of = {str(r): t for t, r in ranks.items()}
        self.model = sentencepiece.SentencePieceProcessor(model_proto=model_proto(ranks))
        self.split = regex.compile(pattern).findall
        #: The ids of a pre-token, as text.
        self.shown: dict[str, str] = {}
        self.held = 0

    def forget(self) -> None:
        self.shown.clear()
        self.held = 0

    def learn(self, new: list[str]) -> None:
        """Encodes pre-tokens not yet seen, all at once."""
        shown, rank = self.shown, self.ranks.get
        rest, spelled = [], []
        for t in new:
            raw = t.encode("utf-8", "surrogatepass")
            r = rank(raw)
            if r is None:
                rest.append(t)
                spelled.append(raw.decode("latin-1"))
            else:
                shown[t] = str(r)
        if "\0" in "".join(spelled):
            spelled = [x.replace("\0", ZERO) for x in spelled]
        name = self.names.__getitem__
        for t, ids in zip(rest, self.model.encode(spelled, out_type=int, num_threads=1) if rest else ()):
            if 0 in ids:
                raise ValueError("the vocabulary lacks a byte of this text")
            shown[t] = " ".join(map(name, ids))
        self.held += 210 * len(new) + 2 * sum(map(len, new)) + sum(map(len, map(shown.__getitem__, new)))

    def ids_text(self, text: str) -> str:
        """The ids of a whole text in decimal, with one space between them."""
        tokens = self.split(text)
        missing = [t for t in set(tokens) if t not in self.shown]
        if missing:
            if self.held > CACHE_BYTES:
                self.forget()
                missing = list(set(tokens))
            self.learn(missing)
        return " ".join(map(self.shown.__getitem__, tokens))

    def encode(self, text: str) -> list[int]:
        return [int(x) for x in self.ids_text(text).split()]

    def decode(self, ids) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def decode_text(self, ids: str) -> bytes:
        """The bytes that ids in decimal stand for."""
        return b"".join(map(self.raw_of.__getitem__, ids.split()))


_CODECS: dict[tuple[str | None, str | None], Codec] = {}


def codec(path: str | None, pattern: str | None) -> Codec:
    """One codec for each worker process, built from the rank file at path; where they are None, this worker's own public one."""
    if (path, pattern) not in _CODECS:
        import public_tokenizers

        _CODECS[path, pattern] = Codec(read_ranks(path or public_tokenizers.path("byte_bpe_50k.tiktoken")), pattern or public_tokenizers.PATTERN)
    return _CODECS[path, pattern]


@contextmanager
def _at_work(path: str | None, pattern: str | None):
    """The codec for one task. Its memory has no cycles and a walk over it would cost more than the work, so the collector rests."""
    c = codec(path, pattern)
    gc.disable()
    try:
        yield c
    finally:
        c.forget()
        gc.enable()


def _encode(path: str | None, pattern: str | None, text_col: str, out_col: str):
    @freed
    def run(batches):
        with _at_work(path, pattern) as c:
            yield from encoded(c, batches)

    def encoded(c, batches):
        for batch in batches:
            place = batch.schema.get_field_index(text_col)
            for at in range(0, batch.num_rows, 256):  # few rows at a time: their ids are Python numbers for a moment
                part = batch.slice(at, 256)
                ids = []
                for value in part.column(place):
                    ids.append(np.fromstring(c.ids_text(value.as_py() or ""), np.int32, sep=" "))
                offsets = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
                yield part.append_column(out_col, pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(ids))))

    return run


def encode_ids(docs: DataFrame, text_col: str = "text", path: str | None = None, pattern: str | None = None, out_col: str = "token_ids") -> DataFrame:
    """All columns of docs and the ids of each whole text as array<int>.

    A null or empty text has no ids. A text or a pre-token of any length is encoded whole. Rows that repeat are each
    encoded, an empty table gives no rows, and a column of docs named out_col gives way. path and pattern: of the
    tokenizer; where they are None every worker finds the public one where it is installed.
    """
    kept = docs.drop(out_col).withColumn(text_col, F.col(text_col).cast("string"))
    schema = T.StructType([*kept.schema.fields, T.StructField(out_col, T.ArrayType(T.IntegerType()))])
    return kept.mapInArrow(_encode(path, pattern, text_col, out_col), schema)


def decode_ids(docs: DataFrame, ids_col: str = "token_ids", path: str | None = None, pattern: str | None = None, out_col: str = "decoded") -> DataFrame:
    """All columns of docs and the bytes that the ids stand for; null ids give no bytes."""

    @F.pandas_udf("binary")
    def raw(rows):
        import pandas as pd

        c = codec(path, pattern)
        return pd.Series([b"" if r is None else c.decode([int(x) for x in r]) for r in rows])

    return docs.drop(out_col).withColumn(out_col, raw(F.col(ids_col)))


def _digest(path: str | None, pattern: str | None):
    @freed
    def run(batches):
        with _at_work(path, pattern) as c:
            yield from digests(c, hashlib.sha256, batches)

    def digests(c, sha, batches):
        for batch in batches:
            n, ids_sha, raw_sha = [], [], []
            for value in batch.column(1):
                ids = c.ids_text(value.as_py() or "")
                n.append(ids.count(" ") + 1 if ids else 0)
                ids_sha.append(sha(ids.encode()).hexdigest())
                raw_sha.append(sha(c.decode_text(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(raw_sha, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def encoding_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every whole text, however long; null counts as empty.

    Rows that repeat an id are each returned; an empty table gives no rows; other columns are not read.
    """
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_digest(path, pattern), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoding_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"))
