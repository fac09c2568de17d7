"""Interpolated modified Kneser-Ney trigram model: counted in Spark, stored as sorted hash arrays, memory-mapped by workers.

Counting.  Tasks hash the words of whole texts (two start marks, one end), count trigrams and words of their part, and send them as packed
blobs to the partition of the trigram's last two words.  There all trigrams with one suffix meet, so the partition knows their counts, the raw
count of the suffix bigram and its continuation count (distinct words before it).  Every n-gram is stored, those seen once as well.

Sums by context.  A second pass over the texts looks the counts up.  What a context keeps after discounts is a sum over its distinct n-grams;
each occurrence of an n-gram seen c times adds one c-th of its term, so tasks send one number for each context they meet, not for each n-gram.
A context that occurs once needs no number: one trigram seen once follows it.  Words get their continuation counts in the same way.

Storing.  Each table is a folder of array files in the shared store, cut by key range: an index by the leading bits of the sorted keys, their
low 32 bits, and their numbers (counts as bytes, larger ones apart).  Workers map them (or copy them first, if the store is not a local file
system, and unlink the copy once it is mapped).

Scoring.  A narrow pass over the texts; look-ups are binary searches.

Defined cases: null and empty texts have one token, the end; repeated rows are learnt as often as they occur; with no training rows every score
rests on the unseen word alone; other columns are ignored.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm.common import held_out, shared_folder
from terse.llm.text_kernel import hashed_words, mix64

_U = np.uint64
START, END = _U(0x0123456789ABCDEF), _U(0xFEDCBA9876543210)
HIGH, LOW = 38, 18
"""Bits of a trigram's key: the high ones tell its last two words, the low ones the word before them."""

CHUNK_BYTES = 4 << 20
"""Bytes of text whose tokens are looked up at once: the more, the fewer visits to each file."""


def _pair(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return mix64(a * _U(0x9E3779B97F4A7C15) + b)


def _keyed(group: np.ndarray, other: np.ndarray) -> np.ndarray:
    return ((group >> _U(64 - HIGH)) << _U(LOW)) | (other >> _U(64 - LOW))


def _pair_key(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Two words' key: the bits by which trigrams are grouped."""
    return _pair(a, b) >> _U(64 - HIGH)


def token_streams(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Per chunk: first and last document, token hashes with two starts before and an end after each document, and document heads."""
    for a, b, words, firsts in hashed_words(column, lower=True, size=CHUNK_BYTES):
        n = np.diff(firsts)
        heads = np.zeros(len(n) + 1, np.int64)
        np.cumsum(n + 3, out=heads[1:])
        out = np.empty(heads[-1], _U)
        out[heads[:-1]] = START
        out[heads[:-1] + 1] = START
        out[heads[1:] - 1] = END
        at = np.arange(len(words)) + np.repeat(heads[:-1] + 2 - firsts[:-1], n)
        out[at] = words
        yield a, b, out, heads


def _targets(heads: np.ndarray) -> np.ndarray:
    """Positions of real tokens (words and ends) in a stream."""
    keep = np.ones(heads[-1], bool)
    keep[heads[:-1]] = False
    keep[heads[:-1] + 1] = False
    return np.flatnonzero(keep)


# ---- packed blobs: sorted distinct keys with counts -------------------------------------------------------------


def _squeezed(values: np.ndarray) -> bytes:
    """The array's bytes, entropy-coded, after their number."""
    raw = np.ascontiguousarray(values).tobytes()
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _expanded(blob: bytes, kind: str) -> np.ndarray:
    size = int.from_bytes(blob[:8], "little")
    return np.frombuffer(pa.decompress(blob[8:], size, codec="zstd", asbytes=True) if size else b"", kind)


def _pack_keys(keys: np.ndarray) -> bytes:
    """Sorted keys as differences in as few bytes as the largest needs, byte by byte: the leading ones are mostly small."""
    gaps = np.diff(keys, prepend=keys[:1])
    width = max(1, (int(gaps.max()).bit_length() + 7) // 8) if len(gaps) else 1
    return bytes([width]) + keys[:1].astype("<u8").tobytes() + _squeezed(gaps.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T)


def _unpack_keys(blob: bytes) -> np.ndarray:
    planes = _expanded(blob[9:], "u1").reshape(blob[0], -1)
    wide = np.zeros((planes.shape[1], 8), np.uint8)
    wide[:, : blob[0]] = planes.T
    return np.frombuffer(blob, "<u8", 1, 1)[0] + np.cumsum(wide.reshape(-1).view("<u8"), dtype=_U)


def pack(keys: np.ndarray, counts: np.ndarray) -> tuple[bytes, bytes, bytes]:
    """Sorted keys, counts as single bytes, and those that need more apart."""
    small = np.minimum(counts, 255).astype(np.uint8)
    return _pack_keys(keys), _squeezed(small), counts[small == 255].astype("<u4").tobytes()


def unpack(keys: bytes, small: bytes, large: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = _expanded(small, "u1").astype(np.int64)
    n[n == 255] = np.frombuffer(large, "<u4")
    return _unpack_keys(keys), n


def _counted(parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of arrays, which are given up for it, and how often each occurs."""
    keys = np.concatenate(parts)
    parts.clear()
    keys.sort()
    heads = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[heads], np.diff(np.append(heads, len(keys)))


def _sum_sorted(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    heads = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, np.int64)
    return keys[heads], (np.add.reduceat(counts, heads) if len(heads) else counts[:0])


BLOB = pa.schema([("part", pa.int32()), ("order", pa.int8()), ("k", pa.binary()), ("p", pa.binary()), ("c", pa.binary())])
WIDTH = {3: HIGH + LOW, 1: 64}
"""Bits of the keys of counted trigrams and words."""
SUM_WIDTH = {3: HIGH, 2: 64, 1: 64}
"""Bits of the keys of sums by two words, by the first word of a bigram, and by its last."""
_BLOB_DDL = "part int, order tinyint, k binary, p binary, c binary"


def _cut(keys: np.ndarray, width: int, bits: int) -> Iterator[tuple[int, slice]]:
    """Ranges of sorted keys by their top ``bits`` of ``width``."""
    parts = (keys >> _U(width - bits)).astype(np.int64)
    cuts = np.concatenate(([0], np.flatnonzero(np.diff(parts)) + 1, [len(keys)])) if len(keys) else np.zeros(1, np.int64)
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        yield int(parts[a]), slice(a, b)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], BLOB.field(i).type) for i in range(5)], schema=BLOB)


def _blobs(keys: np.ndarray, counts: np.ndarray, order: int, bits: int) -> pa.RecordBatch:
    """Counts, one row for each range of keys, so that equal groups meet."""
    return _batch([(part, order, *pack(keys[at], counts[at])) for part, at in _cut(keys, WIDTH[order], bits)])


def _sum_blobs(keys: np.ndarray, sums: list[np.ndarray], order: int, bits: int) -> pa.RecordBatch:
    """One or two sums for each key, one row for each range of keys."""
    empty = np.zeros(0)
    first, second = (*sums, empty)[:2]
    return _batch([(part, order, _pack_keys(keys[at]), _squeezed(first[at]), _squeezed(second[at])) for part, at in _cut(keys, SUM_WIDTH[order], bits)])


def _rows(table: pa.Table, order: int) -> list[tuple[bytes, bytes, bytes]]:
    return [(k, p, c) for o, k, p, c in zip(*(table.column(x).to_pylist() for x in ("order", "k", "p", "c")), strict=True) if o == order]


def _merged(table: pa.Table, order: int) -> tuple[np.ndarray, np.ndarray]:
    """All keys of one order with their counts added up."""
    rows = [unpack(*r) for r in _rows(table, order)]
    if not rows:
        return np.zeros(0, _U), np.zeros(0, np.int64)
    return _sum_sorted(np.concatenate([r[0] for r in rows]), np.concatenate([r[1] for r in rows]))


def _merged_sums(table: pa.Table, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All keys of one order with their two sums (zeros where there is one) added up."""
    rows = _rows(table, order)
    if not rows:
        return np.zeros(0, _U), np.zeros(0), np.zeros(0)
    keys, at = np.unique(np.concatenate([_unpack_keys(k) for k, _, _ in rows]), return_inverse=True)
    first, second = (np.concatenate([_expanded(r[k], "<f8") for r in rows]) for k in (1, 2))
    second = second if len(second) else np.zeros(len(first))
    return keys, np.bincount(at, first, len(keys)), np.bincount(at, second, len(keys))


def _group_heads(keys: np.ndarray) -> np.ndarray:
    top = keys >> _U(LOW)
    return np.flatnonzero(np.concatenate(([True], top[1:] != top[:-1]))) if len(top) else np.zeros(0, np.int64)


def _sums(values: np.ndarray, heads: np.ndarray) -> np.ndarray:
    return np.add.reduceat(values, heads) if len(heads) else values[:0]


# ---- array files ---------------------------------------------------------------------------------------------------


def _store(folder: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(folder)


def save_arrays(folder: str, name: str, arrays: list[np.ndarray]) -> None:
    """Writes arrays into one file under a private name and moves it into place: a task that runs twice leaves the same file."""
    store, root = _store(folder)
    store.create_dir(root, recursive=True)
    private = f"{root}/_{uuid.uuid4().hex}"
    with store.open_output_stream(private) as f:
        f.write(np.array([x.nbytes for x in arrays], "<i8").tobytes())
        for values in arrays:
            if len(values):
                f.write(np.ascontiguousarray(values).data.cast("B"))
            f.write(bytes(-values.nbytes % 8))
    store.move(private, f"{root}/{name}")


_MAPPED: dict[str, list[np.ndarray]] = {}


def mapped(folder: str, name: str, kinds: list[str]) -> list[np.ndarray]:
    """The arrays of a stored file, memory-mapped; kept for the worker's later tasks.  Empty where there is no file."""
    key = f"{folder}/{name}"
    if key not in _MAPPED:
        if len(_MAPPED) > 32_000:
            _MAPPED.clear()
        store, root = _store(folder)
        path, copy = f"{root}/{name}", None
        there = store.get_file_info(path).type == fs.FileType.File
        if there and not isinstance(store, fs.LocalFileSystem):
            handle, copy = tempfile.mkstemp()
            os.close(handle)
            fs.copy_files(path, copy, source_filesystem=store, destination_filesystem=fs.LocalFileSystem())
            path = copy
        out = [np.zeros(0, kind) for kind in kinds]
        if there:
            raw = np.asarray(np.memmap(path, np.uint8, mode="r"))
            at = 8 * len(kinds)
            for k, size in enumerate(raw[:at].view("<i8").tolist()):
                out[k] = raw[at : at + size].view(kinds[k])
                at += size + -size % 8
        if copy:
            os.unlink(copy)  # the mapping keeps the bytes; nothing is left behind
        _MAPPED[key] = out
    return _MAPPED[key]


class RangeTable:
    """Sorted keys with numbers, in 2**bits files by the keys' top bits.

    A file's index tells where the keys of each value of their further bits begin, down to the last 32, which it holds.  Keys of 64 bits are
    held whole.  Numbers of kind ``u1`` are counts: bytes, with those of 255 and more in a list apart.
    """

    def __init__(self, folder: str, table: str, bits: int, width: int, values: dict[str, str]):
        self.folder, self.table, self.bits, self.width, self.values = folder, table, bits, width, values
        self.whole = width == 64
        self.low = width - bits
        self.kinds = ["<u4", "<u8" if self.whole else "<u4"]
        for kind in values.values():
            self.kinds += [kind, "<i8"]

    def _places(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index cell and held bits of keys of one file."""
        own = keys & _U((1 << self.low) - 1)
        return (own >> _U(32)).astype(np.int64), (own & _U(0xFFFFFFFF)).astype("<u4")

    def save(self, part: int, keys: np.ndarray, **values: np.ndarray) -> None:
        if self.whole:
            arrays = [np.zeros(0, "<u4"), keys.astype("<u8")]
        else:
            cells, held = self._places(keys)
            index = np.zeros((1 << max(0, self.low - 32)) + 1, "<u4")
            np.cumsum(np.bincount(cells, minlength=len(index) - 1), out=index[1:], dtype="<u4")
            arrays = [index, held]
        for name, kind in self.values.items():
            n, big = values[name], np.zeros(0, np.int64)
            if kind == "u1":
                big = np.flatnonzero(n >= 255)
                big = np.concatenate((big, n[big]))
                n = np.minimum(n, 255)
            arrays += [n.astype(kind), big.astype("<i8")]
        save_arrays(self.folder, f"{self.table}-{part}", arrays)

    def _search(self, index: np.ndarray, own: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where each key is, and whether it is there."""
        if self.whole or len(index) == 2:
            held = asked if self.whole else self._places(asked)[1]
            at = np.minimum(np.searchsorted(own, held), len(own) - 1)
            return at, own[at] == held
        cells, held = self._places(asked)
        low, end = index[cells].astype(np.int64), index[cells + 1].astype(np.int64)
        high, last = end.copy(), len(own) - 1
        for _ in range(int((end - low).max()).bit_length()):
            mid = (low + high) >> 1
            less = (own[np.minimum(mid, last)] < held) & (low < high)
            low = np.where(less, mid + 1, low)
            high = np.where(less, high, mid)
        at = np.minimum(low, last)
        return at, (low < end) & (own[at] == held)

    def find(self, keys: np.ndarray) -> dict[str, np.ndarray]:
        """The numbers of each key, 0 where it is unknown."""
        out = {v: np.zeros(len(keys), np.float64 if "f" in kind else np.int64) for v, kind in self.values.items()}
        order = np.argsort(keys)
        asked = keys[order]
        edges = np.arange(1 << self.bits, dtype=_U) << _U(self.width - self.bits)
        cuts = np.append(np.searchsorted(asked, edges), len(asked))
        for part in np.flatnonzero(np.diff(cuts)):
            a, b = cuts[part], cuts[part + 1]
            index, own, *numbers = mapped(self.folder, f"{self.table}-{part}", self.kinds)
            if not len(own):
                continue
            at, hit = self._search(index, own, asked[a:b])
            at, place = at[hit], order[a:b][hit]
            for k, (v, kind) in enumerate(self.values.items()):
                n = numbers[2 * k][at]
                if kind == "u1":
                    n = n.astype(np.int64)
                    big = np.flatnonzero(n == 255)
                    if len(big):
                        where, large = numbers[2 * k + 1].reshape(2, -1)
                        n[big] = large[np.searchsorted(where, at[big])]
                out[v][place] = n
        return out


# ---- counting ------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Model:
    """Where the tables lie and the numbers that go with them."""

    folder: str
    bits: int
    documents: int = 0
    tokens: int = 0
    words: int = 0
    pairs: int = 0
    discounts: tuple[tuple[float, float, float], ...] = ((0.5, 1.0, 1.5),) * 3
    uniform: float = 1.0

    def table(self, name: str) -> RangeTable:
        width, values = {
            "tri": (HIGH + LOW, {"n": "u1"}),
            "bi": (HIGH, {"raw": "u1", "cont": "u1"}),
            "uni": (64, {"raw": "<i8"}),
            "ctx3": (HIGH, {"mass": "<f8"}),
            "ctx2": (64, {"total": "<i8", "mass": "<f8"}),
            "ends": (64, {"cont": "<i8"}),
        }[name]
        return RangeTable(self.folder, name, self.bits, width, values)

    def less(self, order: int, counts: np.ndarray) -> np.ndarray:
        """Counts after the discount of their class; 0 stays 0."""
        d = np.array([0.0, *self.discounts[order - 1]])
        return np.maximum(counts - d[np.minimum(counts, 3)], 0.0)


FLUSH = 8_000_000
"""Tokens that a task holds before it sends what it has counted."""


def _flushed(batches: Iterator[pa.RecordBatch], take, send) -> Iterator[pa.RecordBatch]:
    size = 0
    for batch in batches:
        for _, _, s, heads in token_streams(batch.column("text")):
            t = _targets(heads)
            take(s, t)
            size += len(t)
            if size >= FLUSH:
                yield from send()
                size = 0
    if size:
        yield from send()


def _count_task(bits: int):
    """Trigrams by their last two words, and words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[np.ndarray]] = {3: [], 1: []}

        def take(s, t):
            held[3].append(_keyed(_pair(s[t - 1], s[t]), mix64(s[t - 2])))
            held[1].append(s[t])

        def send():
            for order, parts in held.items():
                yield _blobs(*_counted(parts), order, bits)

        return _flushed(batches, take, send)

    return run


SUMMARY = "name string, n bigint"


def _summary(pairs: dict[str, int]) -> pa.Table:
    return pa.table({"name": pa.array(list(pairs), pa.string()), "n": pa.array([int(v) for v in pairs.values()], pa.int64())})


def _classes(prefix: str, counts: np.ndarray) -> dict[str, int]:
    return {f"{prefix}{k}": int((counts == k).sum()) for k in (1, 2, 3, 4)}


def _store_task(model: Model):
    """Of one key range: stores trigrams, bigrams and words with their counts; reports totals."""

    def run(table: pa.Table) -> pa.Table:
        part = table.column("part")[0].as_py()
        keys, counts = _merged(table, 3)
        heads = _group_heads(keys)
        sizes = np.diff(np.append(heads, len(keys)))
        model.table("tri").save(part, keys, n=counts)
        model.table("bi").save(part, keys[heads] >> _U(LOW), raw=_sums(counts, heads), cont=sizes)
        told = _classes("t", counts) | _classes("b", sizes)
        words, n = _merged(table, 1)
        model.table("uni").save(part, words, raw=n)
        return _summary(told | {"tokens": int(n.sum()), "words": len(words), "pairs": len(heads)})

    return run


def _before(model: Model, s: np.ndarray, t: np.ndarray, raw: np.ndarray) -> np.ndarray:
    """How often the two words before each token occur, from the counts of the bigrams that end at the tokens."""
    seen = np.zeros(len(s), np.int64)
    seen[t] = raw
    before = seen[t - 1]
    before[s[t - 1] == START] = model.documents
    return before


def _summed(parts: list[tuple[np.ndarray, ...]]) -> tuple[np.ndarray, list[np.ndarray]]:
    """Distinct keys with the sums of what goes with them."""
    keys, at = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    return keys, [np.bincount(at, np.concatenate([p[k] for p in parts]), len(keys)) for k in range(1, len(parts[0]))]


def _context_task(model: Model):
    """Sums over distinct n-grams: what is kept by two words' followers, the followers' total and kept part by word, and distinct words before a word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {3: [], 2: [], 1: []}

        def take(s, t):
            u, v, w = s[t - 2], s[t - 1], s[t]
            two = model.table("bi").find(_pair_key(v, w))
            raw = np.maximum(two["raw"], 1)
            some = np.flatnonzero(_before(model, s, t, two["raw"]) > 1)
            n = np.maximum(model.table("tri").find(_keyed(_pair(v[some], w[some]), mix64(u[some])))["n"], 1)
            for order, part in ((3, (_pair_key(u[some], v[some]), model.less(3, n) / n)), (2, (v, two["cont"] / raw, model.less(2, two["cont"]) / raw)), (1, (w, 1.0 / raw))):
                keys, sums = _summed([part])
                held[order].append((keys, *sums))

        def send():
            for order, parts in held.items():
                keys, sums = _summed(parts)
                parts.clear()
                yield _sum_blobs(keys, sums, order, model.bits)

        return _flushed(batches, take, send)

    return run


def _mass_task(model: Model):
    """Of one range: stores the sums by context and the continuation counts of words; reports their classes."""

    def run(table: pa.Table) -> pa.Table:
        part = table.column("part")[0].as_py()
        keys, mass, _ = _merged_sums(table, 3)
        model.table("ctx3").save(part, keys, mass=mass)
        keys, total, mass = _merged_sums(table, 2)
        model.table("ctx2").save(part, keys, total=np.rint(total), mass=mass)
        keys, cont, _ = _merged_sums(table, 1)
        cont = np.rint(cont).astype(np.int64)
        model.table("ends").save(part, keys, cont=cont)
        return _summary(_classes("u", cont))

    return run


def _discounts(n: dict[str, int], prefix: str) -> tuple[float, float, float]:
    """The three discounts of modified smoothing, from how many n-grams have counts 1 to 4; plain halves where those are lacking."""
    n1, n2, n3, n4 = (n.get(f"{prefix}{k}", 0) for k in (1, 2, 3, 4))
    if not (n1 and n2 and n3):
        return (0.5, 1.0, 1.5)
    y = n1 / (n1 + 2 * n2)
    out = (1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3)
    return tuple(min(max(d, 0.05), k - 0.05) for k, d in enumerate(out, 1))


def fit(train: DataFrame, keys_per_range: int = 3_000_000) -> Model:
    """Counts the texts of ``train`` (column text) and stores the model in the shared folder."""
    folder = f"{shared_folder(train.sparkSession)}/kneser-ney"
    texts = train.select(F.coalesce("text", F.lit("")).alias("text"))
    n_docs, n_bytes = texts.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0))).first()
    bits = min(16, max(6, int(n_bytes / 5 / keys_per_range).bit_length()))
    model = Model(folder, bits, n_docs)

    def told(task, then) -> dict[str, int]:
        out = texts.mapInArrow(task, _BLOB_DDL).groupBy("part").applyInArrow(then, SUMMARY)
        return {r["name"]: r["n"] for r in out.groupBy("name").agg(F.sum("n").alias("n")).collect()}

    n = told(_count_task(bits), _store_task(model))
    high = tuple(_discounts(n, k) for k in "bt")
    model = replace(model, tokens=n.get("tokens", 0), words=n.get("words", 0), pairs=n.get("pairs", 0), discounts=(model.discounts[0], *high))
    u = told(_context_task(model), _mass_task(model))
    low = _discounts(u, "u")
    # what the lowest order takes off all words goes to the unseen, evenly over the words and one more
    three = model.words - u.get("u1", 0) - u.get("u2", 0)
    spare = (low[0] * u.get("u1", 0) + low[1] * u.get("u2", 0) + low[2] * three) / model.pairs if model.pairs else 1.0
    return replace(model, discounts=(low, *high), uniform=spare / (model.words + 1))


# ---- scoring -------------------------------------------------------------------------------------------------------


def token_probabilities(model: Model, s: np.ndarray, heads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Probability of every real token of a stream, and its count in training."""
    t = _targets(heads)
    u, v, w = s[t - 2], s[t - 1], s[t]
    p = (model.less(1, model.table("ends").find(w)["cont"]) / model.pairs if model.pairs else 0.0) + model.uniform
    two = model.table("bi").find(_pair_key(v, w))
    ctx = model.table("ctx2").find(v)
    total = np.maximum(ctx["total"], 1)
    p = np.where(ctx["total"] > 0, model.less(2, two["cont"]) / total + (1 - ctx["mass"] / total) * p, p)
    before = _before(model, s, t, two["raw"])
    mass = np.full(len(t), model.less(3, np.ones(1, np.int64))[0])
    some = np.flatnonzero(before > 1)
    mass[some] = model.table("ctx3").find(_pair_key(u[some], v[some]))["mass"]
    some = np.flatnonzero(before > 0)
    n = model.table("tri").find(_keyed(_pair(v[some], w[some]), mix64(u[some])))["n"]
    p[some] = model.less(3, n) / before[some] + (1 - mass[some] / before[some]) * p[some]
    return np.maximum(p, 1e-300), model.table("uni").find(w)["raw"]


SCORES = "doc_id bigint, n_tokens bigint, n_known bigint, base_score double, score double"


def score(docs: DataFrame, model: Model) -> DataFrame:
    """Per document: doc_id, n_tokens, n_known, base_score (add-one word model) and score, log10 probabilities of the whole text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        floor = np.log10(model.tokens + model.words + 1.0)
        for batch in batches:
            ids = batch.column("doc_id")
            for a, b, s, heads in token_streams(batch.column("text")):
                p, count = token_probabilities(model, s, heads)
                starts = heads[:-1] - 2 * np.arange(len(heads) - 1)
                add = lambda x, starts=starts: np.add.reduceat(x, starts)
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(a, b - a), pa.array(np.diff(heads) - 2), pa.array(add((count > 0).astype(np.int64))), pa.array(add(np.log10(count + 1.0) - floor)), pa.array(add(np.log10(p)))],
                    names=["doc_id", "n_tokens", "n_known", "base_score", "score"],
                )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, SCORES)


def op7_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    out = held_out(F.col("doc_id"), 7, 2)
    model = fit(docs.where(~out))
    return score(docs, model).select("doc_id", out.alias("held_out"), "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score")
