"""Benchmark decontamination: SimHash of item-sized windows, multi-index Hamming search, exact weighted-shingle check.

Windows.  Benchmark items fall into size classes.  A class has a window length and a stride; every document is cut into windows of that
length at all multiples of the stride, and an item is represented by the windows at its first ``stride`` offsets (and its last ones), so a
passage is met by an equal window wherever it stands.  A window's fingerprint has 64 bits: signs of the sums of its words' hash bits.

Search.  Fingerprints within ``radius`` bits agree in one of ``radius + 1`` bit blocks (64 bits cut evenly), so looking up each block finds all of them;
the Hamming distance is then checked.

Sure windows.  An edit can change all of an item's few windows, so the search also looks up single shingles at every word of a document.  A passage at the
similarity or above lacks so few of the item's shingles that, of any greater number of them, one is left untouched: so many are indexed, the rarest first.
Where one is met, the passage may begin at any word near; all of these beginnings are bounded by the shingles they share, and the best are checked.

Check.  The document's words where the whole item would stand are compared with the item: sum of the smaller over sum of the larger
weights of their five-word shingles (weight: occurrences), exactly.

The benchmark is a stated query set: it is taken in blocks of ``items_at_once``, so what is broadcast has a fixed bound.

Defined cases: words are runs without ASCII blanks and punctuation, A-Z lower-cased; null and empty texts match nothing; an item shorter than a shingle is one
shingle; items without a word match nothing; repeated items and documents are each reported; empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm.common import without
from terse.llm.text_kernel import BLANKS, _byte_values, doc_chunks, utf8_buffer, word_hashes, word_spans

_U = np.uint64
_MIX = _U(0x9E3779B97F4A7C15)

SEPARATORS = BLANKS.copy()
SEPARATORS[[b for b in range(33, 127) if not chr(b).isalnum()]] = True
_VALUES = _byte_values(lower=True)
_VALUES[SEPARATORS] = 0

# fixed values: (window words, stride) of the size classes; a class takes items of window + stride - 1 words or more
CLASSES = ((5, 1), (8, 2), (12, 3), (16, 4), (24, 6), (32, 8), (48, 12), (64, 16), (96, 24), (128, 32), (256, 64))


@dataclass(frozen=True)
class LeakRule:
    width: int = 5
    similarity: float = 0.8
    radius: int = 3
    items_at_once: int = 20_000


def plain_words(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Per chunk of documents: first, last, word hashes (punctuation parts words) and first words."""
    raw, offsets = utf8_buffer(column)
    for a, b in doc_chunks(offsets, 1 << 18):
        part, own = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, _, firsts = word_spans(part, own, SEPARATORS)
        yield a, b, word_hashes(part, starts, True, _VALUES), firsts


def _bit_sums(hashes: np.ndarray) -> np.ndarray:
    """Running sums of +1 and -1 by bit, modulo 2**16 (differences of near places are exact)."""
    bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1).view(np.int8)
    out = np.zeros((len(hashes) + 1, 64), np.int16)
    np.cumsum(bits, axis=0, dtype=np.int16, out=out[1:])
    return out


def fingerprints(sums: np.ndarray, starts: np.ndarray, length: int) -> np.ndarray:
    """SimHash of the windows at ``starts``: a bit is set if more than half of the words have it."""
    ones = sums[starts + length] - sums[starts]
    return np.packbits(ones * np.int16(2) > length, axis=1).view(np.uint64).reshape(-1)


def _shingles(words: np.ndarray, width: int) -> Counter:
    n = len(words)
    if n == 0:
        return Counter()
    k = min(width, n)
    return Counter(tuple(words[i : i + k].tolist()) for i in range(n - k + 1))


def shingle_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """A hash of the ``width`` words from every word on, across document borders."""
    n = max(len(words) - width + 1, 0)
    out = np.zeros(n, _U)
    for i in range(width):
        out = (out ^ words[i : i + n]) * _MIX
        out ^= out >> _U(29)
    return out


def weighted_similarity(a: Counter, b: Counter) -> float:
    low = sum(min(n, b[s]) for s, n in a.items())
    high = sum(a.values()) + sum(b.values()) - low
    return low / high if high else 0.0


@dataclass
class ItemIndex:
    """The items of one block, by size class: fingerprints with the item and offset, and tables by bit block."""

    rule: LeakRule
    ids: list = field(default_factory=list)
    words: list[np.ndarray] = field(default_factory=list)
    shingles: list[Counter] = field(default_factory=list)
    tables: dict = field(default_factory=dict)
    sure: dict = field(default_factory=dict)

    @classmethod
    def build(cls, items: pa.Table, rule: LeakRule) -> ItemIndex:
        self = cls(rule)
        rows: dict[tuple[int, int], list[tuple[int, int, int]]] = {}
        ids = items.column("item_id").to_pylist()
        column = items.column("text").combine_chunks()
        for a, b, h, firsts in plain_words(column):
            for d in range(a, b):
                w = h[firsts[d - a] : firsts[d - a + 1]]
                if not len(w):
                    continue
                k = len(self.ids)
                self.ids.append(ids[d])
                self.words.append(w)
                self.shingles.append(_shingles(w, rule.width))
                fit = [c for c in CLASSES if c[0] + c[1] - 1 <= len(w)]
                length, stride = fit[-1] if fit else (len(w), 1)
                sums = _bit_sums(w)
                last = len(w) - length
                offsets = np.unique([o for s in range(stride) for o in (s, last - s) if 0 <= o <= last])
                for o, f in zip(offsets, fingerprints(sums, offsets, length), strict=True):
                    rows.setdefault((length, stride), []).append((int(f), k, int(o)))
        n_blocks = rule.radius + 1
        cuts = [64 * i // n_blocks for i in range(n_blocks + 1)]
        for key, found in rows.items():
            prints = np.array([r[0] for r in found], _U)
            item, offset = np.array([r[1] for r in found]), np.array([r[2] for r in found])
            blocks = []
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                part = ((prints >> _U(lo)) & _U((1 << (hi - lo)) - 1)).astype(np.int64)
                order = np.argsort(part, kind="stable")
                heads = np.searchsorted(part[order], np.arange((1 << (hi - lo)) + 1)).astype(np.int32)
                blocks.append((lo, hi, order.astype(np.int32), heads))
            self.tables[key] = (prints, item, offset, blocks)
        self._index_sure()
        return self

    def _index_sure(self) -> None:
        """Per shingle width: sorted hashes of the indexed shingles, and the item of each."""
        for width in {min(self.rule.width, len(w)) for w in self.words}:
            own = {k: shingle_hashes(w, width) for k, w in enumerate(self.words) if min(self.rule.width, len(w)) == width}
            values, count = np.unique(np.concatenate([np.unique(h) for h in own.values()]), return_counts=True)
            found = []
            for k, h in own.items():
                lacking = len(h) - math.ceil(self.rule.similarity * len(h) - 1e-9)
                rarest = np.argsort(count[np.searchsorted(values, h)], kind="stable")[: lacking + 1]
                found += [(int(x), k) for x in np.unique(h[rarest])]
            found.sort()
            self.sure[width] = (np.array([x for x, _ in found], _U), np.array([k for _, k in found]))

    def passages(self, words: np.ndarray, firsts: np.ndarray, owner: np.ndarray, best: dict) -> None:
        """Puts the best passage of each (document, item) at the similarity or above into ``best``."""
        for width, (stored, item) in self.sure.items():
            hashes = shingle_hashes(words, width)
            if not len(hashes):
                continue
            met = np.flatnonzero(stored[np.minimum(np.searchsorted(stored, hashes), len(stored) - 1)] == hashes)
            met = met[owner[met] == owner[met + width - 1]]
            lo, hi = np.searchsorted(stored, hashes[met]), np.searchsorted(stored, hashes[met], side="right")
            places: dict[tuple[int, int], list[int]] = {}
            for p, i, j in zip(met.tolist(), lo.tolist(), hi.tolist(), strict=True):
                for k in item[i:j].tolist():
                    places.setdefault((int(owner[p]), k), []).append(p)
            for (d, k), at in places.items():
                found = self._best_passage(words, hashes, int(firsts[d]), int(firsts[d + 1]), k, np.array(at), width, best.get((d, k), (0.0, 0, 0))[0])
                if found:
                    best[d, k] = found

    def _best_passage(self, words, hashes, first, last, k, at, width, least) -> tuple[float, int, int] | None:
        """The best passage of item k over the places ``at`` of its shingles in the document from first to last, if better than ``least``."""
        n, total = len(self.words[k]), len(self.words[k]) - width + 1
        lo, hi = max(first, int(at[0]) - n), min(last, int(at[-1]) + n + width)
        own = np.unique(shingle_hashes(self.words[k], width))
        here = hashes[lo : hi - width + 1]
        shared = np.concatenate(([0], np.cumsum(own[np.minimum(np.searchsorted(own, here), len(own) - 1)] == here)))
        reach = np.zeros(hi - lo + 1 + n, np.int64)  # beginnings (from lo - n on) from which a passage covers one of the places
        np.add.at(reach, at - lo + width, 1)
        np.add.at(reach, at - lo + n + 1, -1)
        starts = np.flatnonzero(np.cumsum(reach)) + lo - n
        a, b = np.maximum(starts, first), np.minimum(starts + n, last)
        fits = b - a >= width
        starts, a, b = starts[fits], a[fits], b[fits]
        common = shared[b - width + 1 - lo] - shared[a - lo]
        bound = common / (total + b - a - width + 1 - common)
        out = None
        for i in np.argsort(-bound, kind="stable"):
            if bound[i] < self.rule.similarity or bound[i] <= least:
                break
            similarity = weighted_similarity(_shingles(words[a[i] : b[i]], self.rule.width), self.shingles[k])
            if similarity >= self.rule.similarity and similarity > least:
                least, out = similarity, (similarity, int(a[i]) - first, int(b[i] - a[i]))
        return out

    def near(self, key: tuple[int, int], asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All (asked, stored) pairs of fingerprints within the radius."""
        prints, _, _, blocks = self.tables[key]
        out = []
        for lo, hi, order, heads in blocks:
            part = ((asked >> _U(lo)) & _U((1 << (hi - lo)) - 1)).astype(np.int64)
            n = heads[part + 1] - heads[part]
            some = np.flatnonzero(n)
            if not len(some):
                continue
            q = np.repeat(some, n[some])
            ends = np.cumsum(n[some])
            at = np.arange(ends[-1]) - np.repeat(ends - n[some], n[some]) + np.repeat(heads[part[some]], n[some])
            s = order[at]
            keep = np.bitwise_count(asked[q] ^ prints[s]) <= self.rule.radius
            out.append(np.stack((q[keep], s[keep])))
        if not out:
            return np.zeros(0, int), np.zeros(0, int)
        both = np.unique(np.concatenate(out, axis=1), axis=1)
        return both[0], both[1]

    def matches(self, words: np.ndarray, firsts: np.ndarray) -> dict[tuple[int, int], tuple[float, int, int]]:
        """Best match of each (document, item): similarity, first word and words of the passage."""
        n = len(words)
        best: dict[tuple[int, int], tuple[float, int, int]] = {}
        if not n:
            return best
        sums = _bit_sums(words)
        owner = np.repeat(np.arange(len(firsts) - 1), np.diff(firsts))
        seen = set()
        for key, (_, item, offset, _) in self.tables.items():
            length, stride = key
            starts = np.arange(0, n - length + 1, stride)
            starts = starts[owner[starts] == owner[starts + length - 1]]
            if not len(starts):
                continue
            q, s = self.near(key, fingerprints(sums, starts, length))
            for start, k in {(int(starts[i]) - int(offset[j]), int(item[j])) for i, j in zip(q, s, strict=True)}:
                d = int(owner[min(max(start + len(self.words[k]) // 2, 0), n - 1)])
                a, b = max(start, int(firsts[d])), min(start + len(self.words[k]), int(firsts[d + 1]))
                if b <= a or (a, b, k) in seen:
                    continue
                seen.add((a, b, k))
                similarity = weighted_similarity(_shingles(words[a:b], self.rule.width), self.shingles[k])
                if similarity >= self.rule.similarity and similarity > best.get((d, k), (0.0, 0, 0))[0]:
                    best[d, k] = (similarity, a - int(firsts[d]), b - a)
        self.passages(words, firsts, owner, best)
        return best


MATCHES = "doc_id bigint, item_id bigint, similarity double, first_word bigint, n_words bigint"


def leaks(docs: DataFrame, benchmark: DataFrame, rule: LeakRule = LeakRule()) -> DataFrame:
    """A row for every document and benchmark item it holds: doc_id, item_id, similarity, and where the passage stands."""
    spark = docs.sparkSession
    n_items = benchmark.count()
    blocks = max(1, -(-n_items // rule.items_at_once))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = None
    for block in range(blocks):
        part = benchmark.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == block).select(F.col("item_id").cast("long").alias("item_id"), "text")
        index = spark.sparkContext.broadcast(ItemIndex.build(part.toArrow(), rule))

        def run(batches: Iterator[pa.RecordBatch], index=index) -> Iterator[pa.RecordBatch]:
            items = index.value
            for batch in batches:
                ids = batch.column("doc_id").to_pylist()
                rows = []
                for a, _, words, firsts in plain_words(batch.column("text")):
                    rows += [(ids[a + d], items.ids[k], *found) for (d, k), found in items.matches(words, firsts).items()]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([r[i] for r in rows], kind) for i, kind in enumerate((pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64()))],
                    names=["doc_id", "item_id", "similarity", "first_word", "n_words"],
                )

        found = texts.mapInArrow(run, MATCHES)
        out = found if out is None else out.unionByName(found)
    return out


def drop_leaks(docs: DataFrame, benchmark: DataFrame, rule: LeakRule = LeakRule()) -> DataFrame:
    """The documents that hold no benchmark item, each row judged by its own text; all columns stay."""
    gone = leaks(docs.select(F.xxhash64("text").alias("doc_id"), "text"), benchmark, rule).select("doc_id").distinct()
    return without(docs, gone, F.xxhash64("text"))


def op6_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
