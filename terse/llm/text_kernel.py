"""Vectorised tokenising and hashing of whole Arrow string columns.

Texts are handled as one UTF-8 buffer with document offsets, so a batch of documents costs a few numpy passes
and no Python object per word.  Words are runs of bytes outside the ASCII blanks (0x20, 0x09-0x0D); blanks never
occur inside a multi-byte UTF-8 sequence, so byte-wise splitting equals splitting by code point.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK = 1 << 20
"""Bytes hashed at once (a document longer than this is still handled whole, in one larger chunk)."""

BLANKS = np.zeros(256, bool)
BLANKS[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

_U = np.uint64
_MULT = 0x9E3779B97F4A7C15
_STEP = 0xD6E8FEB86659FD93  # odd, so it has an inverse modulo 2**64
_MASK = (1 << 64) - 1


def mix64(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values."""
    h = (h ^ (h >> _U(32))) * _U(0xD6E8FEB86659FD93)
    h = (h ^ (h >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return h ^ (h >> _U(32))


def _byte_values(lower: bool) -> np.ndarray:
    """One random 64-bit value per byte, none for blanks; with ``lower`` A-Z share the values of a-z."""
    values = mix64(np.arange(1, 257, dtype=_U) * _U(_MULT))
    if lower:
        values[65:91] = values[97:123]
    values[BLANKS] = 0
    return values


_VALUES = {flag: _byte_values(flag) for flag in (False, True)}
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the step and of its inverse, up to n of each."""
    if len(_POWERS.get("up", ())) < n:
        size = max(CHUNK + 1, n)
        for name, base in (("up", _STEP), ("down", pow(_STEP, -1, 1 << 64))):
            out = np.ones(size, _U)
            filled = 1
            while filled < size:
                take = min(filled, size - filled)
                out[filled : filled + take] = out[:take] * _U(pow(base, filled, 1 << 64))
                filled += take
            _POWERS[name] = out
    return _POWERS["up"], _POWERS["down"]


def utf8_buffer(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (one more than documents) of a string or binary column; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    kind = pa.large_binary()
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    if pa.types.is_string(column.type):
        column = column.cast(pa.large_string())
    column = column.cast(kind)
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, column.offset * 8)
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def doc_chunks(offsets: np.ndarray, size: int = CHUNK) -> Iterator[tuple[int, int]]:
    """Ranges of documents whose bytes together stay near ``size``; never splits a document."""
    n, at = len(offsets) - 1, 0
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + size, side="right")) - 1
        end = min(n, max(at + 1, end))
        yield at, end
        at = end


def word_spans(raw: np.ndarray, offsets: np.ndarray, blank: np.ndarray = BLANKS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte starts and ends of all words and, per document, the index of its first word (one more than documents)."""
    n = len(raw)
    solid = np.zeros(n + 1, bool)
    np.logical_not(blank[raw], out=solid[:n])
    prior = np.zeros(n + 1, bool)
    prior[1:] = solid[:n]
    cut = offsets[1:-1]
    begins = solid & ~prior
    ends = ~solid & prior
    if len(cut):
        inner = cut[(cut > 0) & (cut < n)]
        joined = inner[solid[inner] & prior[inner]]
        begins[joined] = True
        ends[joined] = True
    starts, stops = np.flatnonzero(begins), np.flatnonzero(ends)
    return starts, stops, np.searchsorted(starts, offsets)


def word_hashes(raw: np.ndarray, starts: np.ndarray, lower: bool, values: np.ndarray | None = None) -> np.ndarray:
    """A 64-bit hash of every word that begins at ``starts``; bytes whose value is 0 must fill the gaps."""
    if not len(starts):
        return np.zeros(0, _U)
    up, down = _powers(len(raw))
    values = _VALUES[lower] if values is None else values
    sums = np.add.reduceat(values[raw] * up[: len(raw)], starts)
    return mix64(sums * down[starts])


def hashed_words(column: pa.Array | pa.ChunkedArray, lower: bool, size: int = CHUNK) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Per chunk of documents: first and last document, word hashes, and first word of each document (and the end)."""
    raw, offsets = utf8_buffer(column)
    for a, b in doc_chunks(offsets, size):
        part, own = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, _, firsts = word_spans(part, own)
        yield a, b, word_hashes(part, starts, lower), firsts


def chain(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all runs of ``width`` consecutive items, wherever they begin (runs may cross documents)."""
    if len(hashes) < width:
        return np.zeros(0, _U)
    last = len(hashes) - width + 1
    out = hashes[:last].copy()
    for k in range(1, width):
        out = mix64(out * _U(_MULT) + hashes[k : k + last])
    return out


def shingle_runs(hashes: np.ndarray, firsts: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of runs inside one document and, per document, the first of its runs.

    A document with fewer words than ``width`` (but at least one) has one run of all its words.
    """
    n_words = np.diff(firsts)
    n_runs = np.where(n_words >= width, n_words - width + 1, np.minimum(n_words, 1))
    heads = np.zeros(len(n_runs) + 1, np.int64)
    np.cumsum(n_runs, out=heads[1:])
    out = np.zeros(heads[-1], _U)
    long = n_words >= width
    every = chain(hashes, width)
    keep = np.zeros(len(hashes) + 1, np.int32)
    np.add.at(keep, firsts[:-1][long], 1)
    np.add.at(keep, firsts[:-1][long] + n_runs[long], -1)
    inside = np.cumsum(keep)[: len(every)] > 0
    target = np.ones(heads[-1], bool)
    for d in np.flatnonzero(~long & (n_words > 0)):
        acc = chain(hashes[firsts[d] : firsts[d + 1]], int(n_words[d]))
        out[heads[d]] = mix64(acc + _U(n_words[d]))[0]
        target[heads[d]] = False
    out[target] = every[inside]
    return out, heads


def sets_per_document(values: np.ndarray, heads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of every document, with the heads of the shortened runs."""
    owner = np.repeat(np.arange(len(heads) - 1), np.diff(heads))
    order = np.lexsort((values, owner))
    v, o = values[order], owner[order]
    fresh = np.ones(len(v), bool)
    fresh[1:] = (v[1:] != v[:-1]) | (o[1:] != o[:-1])
    v, o = v[fresh], o[fresh]
    out = np.zeros(len(heads), np.int64)
    np.cumsum(np.bincount(o, minlength=len(heads) - 1), out=out[1:])
    return v, out
