"""Words of texts of Latin-1 characters: numpy over the bytes of an Arrow string column. They are those of postings.words_of(), repeats included."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes handled at once, so that the arrays of a piece stay small; a longer text is one piece of its own.
PIECE = 1 << 20
#: Texts with a character that matches have their words from Spark.
BEYOND = r"[^\x00-\xff]"
_CHARACTERS = [chr(c) for c in range(256)]
#: Fixed by Unicode for these characters: letters and numbers; a capital is 32 below its small letter.
WORD = np.array([c.isalnum() for c in _CHARACTERS])
CAPITAL = np.array([c.lower() != c for c in _CHARACTERS])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[:128][CAPITAL[:128]] += 32


def words(texts: pa.Array) -> tuple[list[pa.Array], np.ndarray]:
    """The words of all texts in order, in pieces, and how many each text has. Null texts have none."""
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    offsets = np.frombuffer(texts.buffers()[1] or bytes(8), np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = np.frombuffer(texts.buffers()[2] or b"", np.uint8)
    found, each, at = [], [np.zeros(0, np.int64)], 0
    while at < len(texts):
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + PIECE, "right")) - 1)
        own, count = _words(data[offsets[at] : offsets[end]], offsets[at : end + 1] - offsets[at])
        found.append(own)
        each.append(count)
        at = end
    return found, np.concatenate(each)


def _words(data: np.ndarray, offsets: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    lower, inside = _LOWER[data], WORD[data]
    first = np.flatnonzero(data >= 0xC0)  # of two bytes
    if len(first):
        character = (data[first] & 3).astype(np.int64) << 6 | data[first + 1] & 63
        inside[first] = inside[first + 1] = WORD[character]
        lower[first + 1] += np.where(CAPITAL[character], 32, 0).astype(np.uint8)
    begins, stops = inside.copy(), inside.copy()
    edges = offsets[1:-1][(offsets[1:-1] > 0) & (offsets[1:-1] < len(data))]
    before, after = inside[:-1].copy(), inside[1:].copy()
    before[edges - 1] = after[edges - 1] = False
    begins[1:] &= ~before
    stops[:-1] &= ~after
    starts = np.flatnonzero(begins)
    size = np.flatnonzero(stops) + 1 - starts
    at = np.concatenate([[0], np.cumsum(size)])
    kind, width = (pa.string(), np.int32) if at[-1] < 1 << 31 else (pa.large_string(), np.int64)
    own = pa.Array.from_buffers(kind, len(size), [None, pa.py_buffer(at.astype(width)), pa.py_buffer(lower[inside])])
    return own.cast(pa.string()), np.diff(np.searchsorted(starts, offsets))
