"""Toxicity by the nearest labelled examples: exact TF-IDF cosine over a block-max inverted index, distance-weighted votes.

Examples are a sample of labelled documents, bounded per class by parameters.  Every word counts: (1 + ln tf) * ln((1 + N) / (1 + df)), document
frequencies taken over all documents, times the word's relevance frequency log2(2 + a / max(1, c)) where a toxic and c clean examples hold it
(``relevance=False`` leaves that factor out).  No word is dropped: one that tells nothing of the classes keeps a factor of 1 or so.  A word that no example
holds weighs as if one document held it, and counts in the norm only.

Index.  Examples are dealt into blocks of like ones.  The postings of a word are kept with block maxima; words that very many examples hold are kept as
columns, their block maxima too.  A batch of documents adds up the postings of its rarer words, bounds every (document, block) pair by that and
the block maxima of the others, scores each document's best blocks, and then exactly those pairs whose bound reaches the document's k-th
best cosine: the k nearest are exact.

A neighbour's vote weighs 1 / (distance + 0.05), distance one less the cosine.  Votes become probabilities by isotonic regression on
further labelled documents, linear between its steps.  Near copies (cosine ``copy`` or more) among the neighbours can raise a score by their own votes,
smoothed by the share of toxic labels.  Neighbours and cosines are kept as evidence.

Defined cases: null and empty texts, and texts that share no word with an example, have no neighbours and get the share of toxic labels among such
texts; ties go to the earlier example of the index; null labels are left out; ids labelled twice count once; without labels every score is 0; other
columns are ignored; rows that repeat are scored alike.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm.common import give_back, held_out, shared_folder, small_batches, without, written
from terse.llm.decontaminate import plain_words

_U = np.uint64


@dataclass(frozen=True)
class NeighbourPlan:
    """toxic, clean: labelled examples in the index at most; calibration: further labelled documents at most; k: neighbours; block: examples in an index
    block; columns: words kept as columns at most; relevance: whether words weigh by their relevance frequency; copy: cosine of a near copy."""

    toxic: int = 2000
    clean: int = 4000
    calibration: int = 4000
    k: int = 15
    block: int = 64
    columns: int = 512
    relevance: bool = True
    copy: float = 0.8


def _terms(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """Per chunk: first document, documents, and for every distinct word of each its document (from 0), hash and count, by document and hash."""
    for a, b, h, firsts in plain_words(column):
        yield a, b - a, *_counted(np.repeat(np.arange(b - a), np.diff(firsts)), h)


def _counted(owner: np.ndarray, term: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (document, term) with counts."""
    if not len(owner):
        return owner, term, owner
    order = np.lexsort((term, owner))
    o, t = owner[order], term[order]
    heads = np.flatnonzero(np.concatenate(([True], (o[1:] != o[:-1]) | (t[1:] != t[:-1]))))
    return o[heads], t[heads], np.diff(np.append(heads, len(o)))


def _looked_up(words: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of hashes among sorted words, and which of them are there."""
    if not len(words):
        return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
    at = np.minimum(np.searchsorted(words, h), len(words) - 1)
    return at, words[at] == h


def like_ones_together(x: np.ndarray, block: int) -> np.ndarray:
    """An order of rows in which blocks hold like ones: halves along the leading direction, again and again."""
    out = []

    def halve(rows: np.ndarray) -> None:
        if len(rows) <= block:
            out.append(rows)
            return
        part = x[rows] - x[rows].mean(0)
        direction = part[np.argmax(np.square(part).sum(1))]
        for _ in range(5):
            direction = part.T @ (part @ direction)
            direction = direction / max(np.sqrt(np.square(direction).sum()), 1e-12)
        order = rows[np.argsort(part @ direction, kind="stable")]
        middle = -(-len(rows) // 2 // block) * block
        halve(order[:middle])
        halve(order[middle:])

    halve(np.arange(len(x)))
    return np.concatenate(out)


class BlockMaxIndex:
    """Unit vectors of n examples over n_terms words, in blocks with the largest weight of every word; ``order`` tells which example stands where."""

    def __init__(self, n: int, doc: np.ndarray, term: np.ndarray, weight: np.ndarray, n_terms: int, block: int, columns: int = 512):
        self.n, self.block, self.n_blocks = n, block, -(-n // block)
        held = np.bincount(term, minlength=n_terms)
        often = np.sort(np.argsort(-held, kind="stable")[:columns])
        self.column = np.full(n_terms, -1, np.int32)
        self.column[often] = np.arange(len(often))
        self.width = self.n_blocks * block
        c = self.column[term]
        held = np.flatnonzero(c >= 0)
        dense = np.zeros((n, len(often)), np.float32)
        dense[doc[held], c[held]] = weight[held]
        self.order = like_ones_together(dense, block)
        del dense
        place = np.empty(n, np.int64)
        place[self.order] = np.arange(n)
        dense = np.zeros((self.width, len(often)), np.float64)
        dense[place[doc[held]], c[held]] = weight[held]
        self.dense = dense.reshape(self.n_blocks, block, len(often))
        self.most = self.dense.max(1)
        rare = np.flatnonzero(c < 0)
        self.doc, term, self.weight = place.astype(np.int32)[doc[rare]], term[rare], weight[rare]
        del c, rare, place
        by = np.lexsort((self.doc, term))
        self.doc, self.weight = self.doc[by], self.weight[by]
        self.first = np.searchsorted(term[by], np.arange(n_terms + 1))
        self.pairs = self.scored = 0

    def nearest(self, owner: np.ndarray, term: np.ndarray, weight: np.ndarray, n: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For n vectors given by (vector, word, weight), by vector: their k examples with the largest cosines above 0 (ties: the place in the index), best first."""
        if not len(owner) or not self.n:
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        work = np.cumsum(np.bincount(owner, self.first[term + 1] - self.first[term], n))
        found, at = [], 0
        while at < n:  # so many vectors at a time that their postings and cosines take a few megabytes each
            end = max(at + 1, min(int(np.searchsorted(work, (work[at - 1] if at else 0) + 250_000, side="right")), at + max(1, 250_000 // self.width)))
            part = slice(*np.searchsorted(owner, (at, end)))
            q, d, c = self._nearest(owner[part] - at, term[part], weight[part], end - at, k)
            found.append((q + at, d, c))
            at = end
        return tuple(np.concatenate([f[i] for f in found]) for i in range(3))

    def _nearest(self, owner, term, weight, m, k):
        lo, spans = self.first[term], self.first[term + 1] - self.first[term]
        ends = np.cumsum(spans)
        post = np.arange(ends[-1]) + np.repeat(lo - ends + spans, spans)
        cells = np.repeat(owner * self.width, spans) + self.doc[post]
        partial = np.bincount(cells, np.repeat(weight, spans) * self.weight[post], m * self.width).reshape(m, self.n_blocks, self.block)
        c = self.column[term]
        q = np.zeros((m, self.dense.shape[2]))
        q[owner[c >= 0], c[c >= 0]] = weight[c >= 0]
        bound = partial.max(2) + q @ self.most.T
        cosine = np.zeros(partial.shape)
        seeds = min(self.n_blocks, -(-k // self.block) + 1)
        todo = np.zeros(bound.shape, bool)
        np.put_along_axis(todo, np.argpartition(-bound, seeds - 1, axis=1)[:, :seeds], True, axis=1)
        todo &= bound > 0
        self._score(todo, partial, q, cosine)
        flat = cosine.reshape(m, -1)
        least = np.partition(flat, self.width - k, axis=1)[:, self.width - k] if self.width > k else np.zeros(m)
        rest = (bound > 0) & ~todo & (bound >= least[:, None] - 1e-9)
        self._score(rest, partial, q, cosine)
        self.pairs += bound.size
        self.scored += int(todo.sum() + rest.sum())
        if self.width > k:
            least = np.partition(flat, self.width - k, axis=1)[:, self.width - k]
        rows, docs = np.nonzero((flat > 0) & (flat >= least[:, None]))
        value = flat[rows, docs]
        by = np.lexsort((docs, -value, rows))
        rows, docs, value = rows[by], docs[by], value[by]
        rank = np.arange(len(rows)) - np.searchsorted(rows, np.arange(m))[rows]
        keep = rank < k
        return rows[keep], self.order[docs[keep]], value[keep]

    def _score(self, todo: np.ndarray, partial: np.ndarray, q: np.ndarray, cosine: np.ndarray) -> None:
        """Exact cosines of the chosen (vector, block) pairs, block by block for all vectors at once."""
        for b in np.flatnonzero(todo.any(0)):
            rows = np.flatnonzero(todo[:, b])
            cosine[rows, b] = partial[rows, b] + q[rows] @ self.dense[b].T


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Non-decreasing fit of y over x by pooling adjacent violators: middles of the steps and their values (with add-half smoothing)."""
    order = np.argsort(x, kind="stable")
    x, y = x[order], y[order]
    steps: list[list[float]] = []  # sum of y, how many, sum of x, largest x
    for xi, yi in zip(x, y, strict=True):
        if steps and steps[-1][3] == xi:
            steps[-1] = [steps[-1][0] + yi, steps[-1][1] + 1, steps[-1][2] + xi, xi]
        else:
            steps.append([yi, 1.0, xi, xi])
        while len(steps) > 1 and steps[-2][0] * steps[-1][1] >= steps[-1][0] * steps[-2][1]:
            last = steps.pop()
            steps[-1] = [steps[-1][0] + last[0], steps[-1][1] + last[1], steps[-1][2] + last[2], last[3]]
    return np.array([s[2] / s[1] for s in steps]), np.array([(s[0] + 0.5 * (s[0] / s[1])) / (s[1] + 0.5) for s in steps])


@dataclass
class NeighbourModel:
    """ids, toxic: the examples; steps: calibration; alone: score without neighbours; share: of toxic labels.  What grows with the examples' words travels packed and is
    unpacked where it is used, so the driver holds little of it: words (sorted hashes), factor (what each weighs besides its count), unseen, postings."""

    plan: NeighbourPlan
    packed: bytes = b""
    ids: np.ndarray = field(default_factory=lambda: np.zeros(0, int))
    toxic: np.ndarray = field(default_factory=lambda: np.zeros(0))
    steps: tuple[np.ndarray, np.ndarray] = (np.array([0.0, 1.0]), np.array([0.05, 0.95]))
    alone: float = 0.0
    share: float = 0.0

    @cached_property
    def _open(self) -> tuple:
        return pickle.loads(zlib.decompress(self.packed)) if self.packed else (np.zeros(0, _U), np.zeros(0), 0.0, None)

    words = property(lambda self: self._open[0])
    factor = property(lambda self: self._open[1])
    unseen = property(lambda self: self._open[2])

    def keep(self, words: np.ndarray, factor: np.ndarray, unseen: float, postings: tuple | None) -> None:
        self.packed = zlib.compress(pickle.dumps((words, factor, unseen, postings)), 1)
        self.__dict__.pop("_open", None)

    @cached_property
    def index(self) -> BlockMaxIndex | None:
        postings = self._open[3]
        if postings is None:
            return None
        sizes, term, weight = postings
        index = BlockMaxIndex(len(sizes), np.repeat(np.arange(len(sizes), dtype=np.int32), sizes), term, weight, len(self.words), self.plan.block, self.plan.columns)
        del sizes, term, weight, postings
        self._open = (*self._open[:3], True)
        give_back()
        return index

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k not in ("_open", "index")}

    def vectors(self, owner: np.ndarray, h: np.ndarray, count: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Unit vectors of documents, over all their words: what remains over the words of the examples."""
        at, hit = _looked_up(self.words, h)
        weight = 1 + np.log(np.maximum(count, 1))
        weight[hit] *= self.factor[at[hit]]
        weight[~hit] *= self.unseen
        norm = np.sqrt(np.bincount(owner, np.square(weight), n))
        return owner[hit], at[hit], weight[hit] / np.maximum(norm[owner[hit]], 1e-12)

    def neighbours(self, owner: np.ndarray, h: np.ndarray, count: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(document, example, cosine) of the nearest examples, best first."""
        if self.index is None:
            return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        return self.index.nearest(*self.vectors(owner, h, count, n), n, self.plan.k)

    def votes(self, q: np.ndarray, near: np.ndarray, cosine: np.ndarray, n: int) -> np.ndarray:
        """Share of toxic votes by distance; nan without neighbours."""
        weight = 1 / (1.05 - np.minimum(cosine, 1.0))
        total = np.bincount(q, weight, n)
        return np.where(total > 0, np.bincount(q, weight * self.toxic[near], n) / np.maximum(total, 1e-12), np.nan)

    def scores(self, q: np.ndarray, near: np.ndarray, cosine: np.ndarray, n: int) -> np.ndarray:
        """Calibrated probabilities."""
        vote = self.votes(q, near, cosine, n)
        likely = np.where(np.isnan(vote), self.alone, np.interp(np.nan_to_num(vote), *self.steps))
        copy = cosine >= self.plan.copy
        weight = 1 / (1.05 - np.minimum(cosine[copy], 1.0))
        copied = (np.bincount(q[copy], weight * self.toxic[near[copy]], n) + self.share) / (np.bincount(q[copy], weight, n) + 1)
        return np.where(np.bincount(q[copy], minlength=n) > 0, np.maximum(likely, copied), likely)


def _document_frequencies(docs: DataFrame, words: np.ndarray) -> tuple[np.ndarray, int]:
    """Over all documents: how many hold each of the words, and how many documents there are."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        total = np.zeros(len(known) + 1, np.int64)
        for batch in batches:
            for _, n, _, h, _ in _terms(batch.column("text")):
                at, hit = _looked_up(known, h)
                total[:-1] += np.bincount(at[hit], minlength=len(known))
                total[-1] += n
        some = np.flatnonzero(total)
        give_back()
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["term", "n"])

    rows = docs.select("text").mapInArrow(run, "term bigint, n bigint").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(len(words) + 1, np.int64)
    out[rows.column("term").to_numpy()] = rows.column("n").to_numpy()
    return out[:-1], int(out[-1])


def _bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Labelled texts as distinct words with counts."""
    for batch in batches:
        for a, n, owner, h, count in _terms(batch.column("text")):
            cuts = np.searchsorted(owner, np.arange(n + 1))
            words = [h[i:j].tobytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
            counts = [count[i:j].astype("<u4").tobytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c).slice(a, n) for c in ("doc_id", "y", "role")), pa.array(words, pa.binary()), pa.array(counts, pa.binary())], names=["doc_id", "y", "role", "words", "counts"])
    give_back()


def fit(docs: DataFrame, labels: DataFrame, usable: Column, plan: NeighbourPlan = NeighbourPlan()) -> NeighbourModel:
    """Index and calibration from a bounded sample of labelled documents that ``usable`` admits (chosen by hash of their id)."""
    known = labels.where(F.col("toxic").isNotNull() & usable).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("y")).withColumn("h", F.xxhash64("doc_id"))
    # a third of the labelled ids calibrates, the rest may be examples; each sample has its bound
    role = F.when(F.pmod(F.col("h"), F.lit(3)) == 0, "calibration").when(F.col("y") == 1, "toxic").otherwise("clean")
    known = known.withColumn("role", role)
    parts = [known.where(F.col("role") == r).orderBy("h", "doc_id").limit(n) for r, n in (("calibration", plan.calibration), ("toxic", plan.toxic), ("clean", plan.clean))]
    small_batches(docs.sparkSession)
    folder = shared_folder(docs.sparkSession)
    chosen = written(parts[0].unionByName(parts[1]).unionByName(parts[2]).select("doc_id", "y", "role"), folder, "labelled")
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").select("doc_id", "y", "role", "text")
    bags = texts.mapInArrow(_bags, texts.select("doc_id", "y", "role").schema.simpleString()[7:-1].replace(":", " ") + ", words binary, counts binary")
    # one task puts the bags of the bounded sample together, so that the driver holds the finished model only
    rows = written(bags, folder, "bags").withColumn("all", F.lit(0)).repartition(1)
    words = np.frombuffer(_one(rows.groupBy("all").applyInArrow(lambda t: _boxed(_example_words(t).tobytes()), "m binary")) or b"", _U)
    total, n_docs = _document_frequencies(docs, words)
    idf = np.log((1 + n_docs) / (1 + total)) if len(total) else np.zeros(0)
    found = _one(rows.groupBy("all").applyInArrow(lambda t: _boxed(pickle.dumps(_built(t, plan, words, idf, float(np.log((1 + n_docs) / 2))))), "m binary"))
    return pickle.loads(found) if found else NeighbourModel(plan)


def _boxed(data: bytes) -> pa.Table:
    give_back()
    return pa.table({"m": pa.array([data], pa.binary())})


def _one(frame: DataFrame) -> bytes | None:
    row = frame.first()
    return bytes(row["m"]) if row else None


def _parts(table: pa.Table) -> tuple[pa.Table, pa.Table]:
    """(examples, calibration rows), examples with toxic ones first."""
    order = pc.sort_indices(table, [("y", "descending"), ("doc_id", "ascending"), ("words", "ascending"), ("counts", "ascending")]).to_numpy()
    calibrates = np.array([r == "calibration" for r in table.column("role").to_pylist()], bool)[order]
    return table.take(order[~calibrates]), table.take(order[calibrates])


def _unpacked(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, word and count of bags."""
    words, counts = ([np.frombuffer(x.as_buffer(), kind) for x in table.column(name)] for name, kind in (("words", _U), ("counts", "<u4")))
    owner = np.repeat(np.arange(len(words)), [len(w) for w in words])
    return owner, np.concatenate([*words, np.zeros(0, _U)]), np.concatenate([*counts, np.zeros(0, "<u4")])


def _example_words(table: pa.Table) -> np.ndarray:
    """Sorted hashes of all words of the examples."""
    return np.unique(_unpacked(_parts(table)[0])[1])


def relevance(y: np.ndarray, doc: np.ndarray, term: np.ndarray, n_terms: int) -> np.ndarray:
    """log2(2 + a / max(1, c)) for words that a toxic and c clean examples hold."""
    a, c = np.bincount(term, y[doc], n_terms), np.bincount(term, 1 - y[doc], n_terms)
    return np.log2(2 + a / np.maximum(c, 1))


def _built(table: pa.Table, plan: NeighbourPlan, words: np.ndarray, idf: np.ndarray, unseen: float) -> NeighbourModel:
    """Index of the examples, and the calibration of votes."""
    examples, checks = _parts(table)
    model = NeighbourModel(plan, share=float(table.column("y").to_numpy().mean()))
    if not len(examples):
        return model
    model.toxic, model.ids, n = examples.column("y").to_numpy().astype(np.float64), examples.column("doc_id").to_numpy().copy(), len(examples)
    owner, h, count = _unpacked(examples)
    factor = idf * relevance(model.toxic, owner, np.searchsorted(words, h), len(words)) if plan.relevance else idf
    model.keep(words, factor, unseen, None)
    doc, term, weight = model.vectors(owner, h, count, n)
    model.keep(words, factor, unseen, (np.bincount(doc, minlength=n), term.astype(np.int32), weight.astype(np.float32)))
    del examples, table, owner, h, count, doc, term, weight
    truth = checks.column("y").to_numpy().astype(np.float64)
    votes = model.votes(*model.neighbours(*_unpacked(checks), len(truth)), len(truth)) if len(truth) else np.zeros(0)
    heard = ~np.isnan(votes)
    if heard.any():
        model.steps = isotonic(votes[heard], truth[heard])
    model.alone = float((truth[~heard].sum() + model.share) / ((~heard).sum() + 1))
    return model


def score(docs: DataFrame, model: NeighbourModel) -> DataFrame:
    """doc_id, score, and the evidence: ids and cosines of the nearest examples."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for a, n, owner, h, count in _terms(batch.column("text")):
                q, near, cosine = m.neighbours(owner, h, count, n)
                heads = pa.array(np.searchsorted(q, np.arange(n + 1)), pa.int32())
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").slice(a, n), pa.array(m.scores(q, near, cosine, n)),
                        pa.ListArray.from_arrays(heads, pa.array(m.ids[near], pa.int64())), pa.ListArray.from_arrays(heads, pa.array(cosine)),
                    ],
                    names=["doc_id", "score", "neighbours", "cosines"],
                )
        m.__dict__.pop("index", None)  # a worker that waits keeps no index
        m.__dict__.pop("_open", None)
        give_back()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id bigint, score double, neighbours array<bigint>, cosines array<double>")


def drop_toxic(docs: DataFrame, model: NeighbourModel, threshold: float = 0.5) -> DataFrame:
    """The documents whose score is below the threshold, each row judged by its own text; all columns stay."""
    kind = docs.select(F.xxhash64("text").alias("doc_id"), "text")
    gone = score(kind, model).where(F.col("score") >= threshold).select(F.col("doc_id").alias("gone")).distinct()
    return without(docs, gone, F.xxhash64("text"))


def op4_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    out = held_out(F.col("doc_id"), 5, 0)
    model = fit(docs, labels, ~out)
    return score(docs, model).select("doc_id", out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
