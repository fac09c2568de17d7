"""N-gram Jaccard join by token-combination prefixes, and its groups.

A document is the set of its word shingles, as 64-bit hashes.  Documents with equal sets form a class; classes are joined.

Order and classes of tokens.  Tokens found in many documents are *frequent* and come last in the global order; others come
first; ties go by hash.  Two sets that share at least alpha tokens share, of their first ``size - alpha + l`` tokens, at least l.  With l = 1
a shared rare token is enough, and rare tokens are indexed singly.  Where a prefix reaches into frequent tokens it is extended by
``divisions`` tokens; frequent tokens are dealt into that many divisions by hash, and pairs of tokens of one division are indexed: of
``divisions + 1`` shared frequent tokens two lie in one division.  Sets too short for that are indexed by single frequent tokens too.

From index to links.  Under rare keys, pairs of classes of like sizes are candidates; the number of indexed tokens that a
pair shares bounds its overlap from above and thins the candidates out exactly.  Under frequent keys (groups of near copies) only edges to one member
of each key are made, so their number stays in proportion to the index.  Connected candidates form clusters; sets travel once to their
cluster, and there a breadth-first search with exact overlaps finds the true components.  Clusters too large for one task are cut into blocks and every pair of blocks is searched.

Defined cases: a text without words (or null) has an empty set and links with nothing; a text shorter than a shingle is one shingle of all its
words; rows that repeat an id or have none are each compared and each returned; the class id of a component all of whose rows lack an id is null;
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from terse.llm.common import bounded, components, give_back, shared_folder, without, written
from terse.llm.text_kernel import hashed_words, mix64, sets_per_document, shingle_runs

_U = np.uint64


@dataclass(frozen=True)
class JoinRule:
    """width: words in a shingle; percent: linked if 100 * overlap >= percent * union; frequent: documents from which a token is frequent
    (grows with the corpus so that at most about two million tokens are); hot: sets under one rare token beyond which it becomes a frequent one;
    divisions: of frequent tokens; block: tokens a task searches at once."""

    width: int = 5
    percent: int = 80
    frequent: int = 64
    hot: int = 2048
    divisions: int = 32
    block: int = 2_000_000


def _sets(batch: pa.RecordBatch, width: int) -> Iterator[tuple[pa.Array, np.ndarray, np.ndarray]]:
    ids = batch.column("doc_id")
    for a, b, h, firsts in hashed_words(batch.column("text"), lower=True):
        yield ids.slice(a, b - a), *sets_per_document(*shingle_runs(h, firsts, width))


def _per_doc(values: np.ndarray, heads: np.ndarray) -> np.ndarray:
    """Wrapping sums of a column of numbers over each document; empty documents have 0."""
    total = np.zeros(len(values) + 1, values.dtype)
    np.cumsum(values, out=total[1:])
    return total[heads[1:]] - total[heads[:-1]]


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def _fingerprint(values: np.ndarray, heads: np.ndarray) -> np.ndarray:
    return mix64(_per_doc(mix64(values ^ _U(0x5851F42D4C957F2D)), heads) + np.diff(heads).astype(_U))


def _common_tokens(width: int):
    """Tokens found in two documents or more of a task's part, with how many."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def out():
            keys = np.concatenate(held)
            held.clear()
            keys.sort()
            heads = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.zeros(0, np.int64)
            keys, n = keys[heads], np.diff(np.append(heads, len(keys)))
            keep = n > 1
            return pa.RecordBatch.from_arrays([_signed(keys[keep]), pa.array(n[keep])], names=["token", "n"])

        for batch in batches:
            for _, v, _ in _sets(batch, width):
                held.append(v)
                size += len(v)
            if size >= 4_000_000:
                yield out()
                size = 0
        if held:
            yield out()
        give_back()

    return run


def frequent_tokens(docs: DataFrame, rule: JoinRule) -> np.ndarray:
    """Sorted hashes of frequent tokens; any fixed list is right, a good one saves work.  Its length is bounded by two million."""
    part = docs.mapInArrow(_common_tokens(rule.width), "token bigint, n bigint").groupBy("token").agg(F.sum("n").alias("n")).where(F.col("n") >= rule.frequent)
    part = written(part, shared_folder(docs.sparkSession), "frequent")
    total = part.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    least = max(rule.frequent, total // 2_000_000)
    found = part.where(F.col("n") >= least).select("token").toArrow()
    return np.sort(found.column("token").to_numpy().view(_U)) if len(found) else np.zeros(0, _U)


def _keys(values: np.ndarray, heads: np.ndarray, frequent: np.ndarray, rule: JoinRule):
    """Index keys of the sets: arrays document, key, position of the (first) token, and whether it comes of frequent tokens."""
    sizes = np.diff(heads)
    owner = np.repeat(np.arange(len(sizes)), sizes)
    if len(frequent):
        at = np.minimum(np.searchsorted(frequent, values), len(frequent) - 1)
        often = frequent[at] == values
    else:
        often = np.zeros(len(values), bool)
    order = np.lexsort((values, often, owner))
    values, often = values[order], often[order]
    place = np.arange(len(values)) - np.repeat(heads[:-1], sizes)
    alpha = -(-sizes * rule.percent // 100)
    first = np.minimum(sizes, sizes - alpha + 1)
    reach = np.zeros(len(sizes), bool)
    some = first > 0
    reach[some] = often[heads[:-1][some] + first[some] - 1]
    # the two ways of indexing frequent tokens overlap in size so that any pair in reach of each other shares one
    short = sizes < 2 * rule.divisions
    single = reach & (sizes * rule.percent <= 2 * rule.divisions * 100)
    paired = reach & ~short
    length = np.minimum(sizes, np.where(paired, first + rule.divisions, first))
    inside = place < length[owner]
    rare = inside & ~often
    alone = often & (place < first[owner]) & single[owner]
    out = [(owner[rare], values[rare], place[rare], np.zeros(int(rare.sum()), bool)), (owner[alone], mix64(values[alone]), place[alone], np.ones(int(alone.sum()), bool))]
    many = np.flatnonzero(inside & often & paired[owner])
    if len(many):
        division = (values[many] % _U(rule.divisions)).astype(np.int64)
        by = np.lexsort((place[many], division, owner[many]))
        many, division = many[by], division[by]
        step = 1
        while True:  # pairs of tokens that lie ``step`` apart within their document and division
            a, b = many[:-step], many[step:]
            same = (owner[a] == owner[b]) & (division[:-step] == division[step:]) if step < len(many) else np.zeros(0, bool)
            if not same.any():
                break
            a, b = a[same], b[same]
            out.append((owner[a], mix64(values[a] * _U(0x9E3779B97F4A7C15) + values[b]), place[a], np.ones(len(a), bool)))
            step += 1
    return [np.concatenate(x) for x in zip(*out, strict=True)]


def _index_task(rule: JoinRule, frequent):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, v, heads in _sets(batch, rule.width):
                prints, sizes = _fingerprint(v, heads), np.diff(heads)
                owner, key, place, often = _keys(v, heads, frequent.value, rule)
                rare = np.bincount(owner[~often], minlength=len(sizes)).astype(np.int32)
                for a in range(0, len(owner), 500_000):
                    o = slice(a, a + 500_000)
                    yield pa.RecordBatch.from_arrays(
                        [_signed(key[o]), _signed(prints[owner[o]]), pa.array(sizes[owner[o]].astype(np.int32)), pa.array(place[o].astype(np.int32)), pa.array(rare[owner[o]]), pa.array(often[o])],
                        names=["key", "class", "size", "place", "rare", "often"],
                    )

    return run


def _numbered(parts: Iterator[tuple]) -> Iterator[tuple[int, tuple]]:
    """Parts of a batch with the place of their first row."""
    at = 0
    for part in parts:
        yield at, part
        at += len(part[0])


def _class_task(rule: JoinRule):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, (ids, v, heads) in _numbered(_sets(batch, rule.width)):
                yield pa.RecordBatch.from_arrays(
                    [ids, batch.column("row").slice(a, len(ids)), pa.array(np.diff(heads)), _signed(_fingerprint(v, heads))], names=["doc_id", "row", "n_shingles", "class"]
                )

    return run


def _set_task(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, v, heads in _sets(batch, width):
                cuts = (heads * 8).tolist()
                raw = v.astype("<u8").tobytes()
                sets = [raw[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([_signed(_fingerprint(v, heads)), pa.array(sets, pa.binary())], names=["class", "tokens"])

    return run


AT_ONCE = 1 << 19
"""Tokens that a search looks at in one step."""


def spanning_links(classes: np.ndarray, sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Edges that connect what is connected by links, found by breadth-first search with exact overlaps."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets], np.int64)
    heads = np.concatenate(([0], np.cumsum(sizes)))
    ids = np.zeros(heads[-1], np.int32)
    tokens = np.unique(np.concatenate(sets)) if n else np.zeros(0)
    for k, s in enumerate(sets):
        ids[heads[k] : heads[k + 1]] = np.searchsorted(tokens, s)
    flag = np.zeros(len(tokens), np.uint8)
    del tokens
    left = np.argsort(sizes, kind="stable")
    edges, queue = [], []
    while len(left) or queue:
        if not queue:
            queue.append(left[0])
            left = left[1:]
        x = queue.pop()
        if not len(left):
            continue
        near = (100 * np.minimum(sizes[left], sizes[x]) >= percent * np.maximum(sizes[left], sizes[x])) & (sizes[left] > 0)
        among = left[near]
        if not len(among):
            continue
        own = ids[heads[x] : heads[x + 1]]
        flag[own] = 1
        linked = np.zeros(len(among), bool)
        ends, at = np.cumsum(sizes[among]), 0
        while at < len(among):
            end = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + AT_ONCE, side="right")))
            spans = sizes[among[at:end]]
            starts = np.concatenate(([0], np.cumsum(spans)[:-1]))
            take = np.arange(spans.sum()) + np.repeat(heads[among[at:end]] - starts, spans)
            shared = np.add.reduceat(flag[ids[take]], starts, dtype=np.int64)
            linked[at:end] = 100 * shared >= percent * (sizes[x] + spans - shared)
            at = end
        flag[own] = 0
        hit = among[linked]
        edges += [(int(classes[x]), int(classes[y])) for y in hit]
        queue += hit.tolist()
        left = left[~np.isin(left, hit)] if len(hit) else left
    return edges


def _search_task(percent: int):
    def run(table: pa.Table) -> pa.Table:
        classes, at = np.unique(table.column("class").to_numpy(), return_index=True)
        column = table.column("tokens")
        sets = [np.frombuffer(column[int(i)].as_buffer(), "<u8") for i in at]
        edges = spanning_links(classes, sets, percent)
        del sets
        if table.nbytes > 1 << 24:
            give_back()
        return pa.table({"a": pa.array([e[0] for e in edges], pa.int64()), "b": pa.array([e[1] for e in edges], pa.int64())})

    return run


def shared_keys(index: DataFrame, folder: str, name: str) -> DataFrame:
    """Rows under rare keys that two classes or more have, each class once."""
    rare = index.where("not often").select("key", "class", "size", "place", "rare")
    met = Window.partitionBy("key")
    some = rare.withColumns({"c0": F.min("class").over(met), "c1": F.max("class").over(met)}).where("c0 <> c1").drop("c0", "c1")
    return written(some.dropDuplicates(["key", "class"]), folder, name)


def candidate_edges(index: DataFrame, some: DataFrame, rule: JoinRule) -> DataFrame:
    """Edges (a, b) between classes such that linked classes are connected by them."""
    p, q = rule.percent, 100 + rule.percent
    x, y = some.alias("x"), some.alias("y")
    alike = 100 * F.least("x.size", "y.size") >= p * F.greatest("x.size", "y.size")
    met = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.class") < F.col("y.class")) & alike)
    counted = met.groupBy(F.col("x.class").alias("a"), F.col("y.class").alias("b")).agg(
        F.count("*").alias("n"), F.first("x.size").alias("sa"), F.first("y.size").alias("sb"), F.first(F.col("x.size") - F.col("x.rare")).alias("ra"), F.first(F.col("y.size") - F.col("y.rare")).alias("rb")
    )
    # of the set whose indexed rare tokens end first, all that are shared have been counted; the rest may be shared at most
    most = F.col("n") + F.greatest("ra", "rb")
    close = counted.where(most * q >= p * (F.col("sa") + F.col("sb"))).select("a", "b")
    often = index.where("often").select("key", "class", "place")
    # the hub of a key is the member with the fewest tokens before it: the least edited copy
    hubs = often.groupBy("key").agg(F.min(F.struct("place", "class"))["class"].alias("hub"), F.max("class").alias("c1"), F.min("class").alias("c0")).where("c0 <> c1")
    stars = often.join(hubs.select("key", "hub"), "key").where("class <> hub").select(F.col("hub").alias("a"), F.col("class").alias("b")).distinct()
    return close.unionByName(stars)


def _index(docs: DataFrame, rule: JoinRule, folder: str) -> tuple[DataFrame, DataFrame]:
    """The written index, and its rows under shared rare keys.  Rare tokens with very many sets (seldom met by single tasks, so not found frequent) become frequent ones, and it is built anew: any
    list of frequent tokens is right, and so no rare token pairs more than ``hot`` sets."""
    spark = docs.sparkSession
    frequent = frequent_tokens(docs, rule)
    for k in range(8):
        shared = spark.sparkContext.broadcast(frequent)
        index = docs.mapInArrow(_index_task(rule, shared), "key bigint, class bigint, size int, place int, rare int, often boolean")
        index = written(index, folder, f"index-{k}")
        some = shared_keys(index, folder, f"rare-{k}")
        busy = some.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > rule.hot)
        found = written(busy.select("key"), folder, f"busy-{k}").toArrow().column("key").to_numpy().view(_U)
        if not len(found):
            break
        frequent = np.union1d(frequent, found)
    return index, some


def _rows(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("row"))


def grouped(docs: DataFrame, rule: JoinRule) -> DataFrame:
    """Per document: doc_id, row (hash of its text), n_shingles, and ``first`` of its component (doc_id, row): the smallest doc_id, null last.  Documents
    without shingles are their own."""
    folder = shared_folder(docs.sparkSession)
    docs = _rows(docs)
    table = written(docs.mapInArrow(_class_task(rule), "doc_id bigint, row bigint, n_shingles bigint, class bigint"), folder, "classes")
    index, some = _index(docs, rule, folder)
    earliest = F.min(F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "row")).alias("first")
    representative = written(table.where("n_shingles > 0").groupBy("class").agg(earliest, F.max("n_shingles").alias("n")), folder, "representatives")
    edges = written(candidate_edges(index, some, rule), folder, "candidates")
    clusters = components(edges, folder, "clusters")
    clusters = clusters.unionByName(clusters.select(F.col("root").alias("node"), "root").distinct())
    member = representative.join(clusters.withColumnRenamed("node", "class"), "class").select("first", "class", "root", "n")
    weight = member.groupBy("root").agg(F.sum("n").alias("weight")).withColumn("blocks", F.ceil(F.col("weight") / rule.block).cast("long")).select("root", "blocks")
    member = written(member.join(weight, "root").withColumn("own", F.pmod(F.xxhash64("class"), F.col("blocks"))), folder, "members")
    # a set meets every other block of its cluster: (i, j) with i <= j; one block means one task
    spread = member.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1))).select(
        "class", "root", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j")
    )
    wanted = written(member.select(F.col("first.doc_id").alias("member_id"), F.col("first.row").alias("member_row")), folder, "member_docs")
    chosen = docs.join(bounded(wanted), F.col("doc_id").eqNullSafe(F.col("member_id")) & (F.col("row") == F.col("member_row")), "left_semi")
    sets = chosen.mapInArrow(_set_task(rule.width), "class bigint, tokens binary")
    placed = sets.join(bounded(written(spread, folder, "spread")), "class").select("root", "i", "j", "class", "tokens")
    links = placed.groupBy("root", "i", "j").applyInArrow(_search_task(rule.percent), "a bigint, b bigint")
    links = written(links, folder, "links")
    joined = components(links, folder, "components")
    class_root = representative.select("class", "first").join(joined.withColumnRenamed("node", "class"), "class", "left").withColumn("root", F.coalesce("root", "class"))
    class_root = written(class_root, folder, "rooted")
    lowest = class_root.groupBy("root").agg(F.min("first").alias("first"))
    named = written(class_root.drop("first").join(lowest, "root").select("class", "first"), folder, "named")
    alone = F.struct(F.col("doc_id").isNull().alias("nameless"), "doc_id", "row")
    return table.join(named, "class", "left").select("doc_id", "row", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("first")).otherwise(alone).alias("first"))


def near_duplicates(docs: DataFrame, rule: JoinRule = JoinRule()) -> DataFrame:
    """Per document: doc_id, n_shingles, component_id (the smallest doc_id reachable by links, itself included)."""
    return grouped(docs, rule).select("doc_id", "n_shingles", F.col("first.doc_id").alias("component_id"))


def keep_first(docs: DataFrame, rule: JoinRule = JoinRule()) -> DataFrame:
    """One document of every component: that with the smallest doc_id (null last), and of rows that repeat id and text one; those without a word all stay; all columns stay."""
    folder = shared_folder(docs.sparkSession)
    groups = written(grouped(docs, rule).where("n_shingles > 0"), folder, "groups")
    first = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("row") == F.col("first.row"))
    kept = without(docs, groups.where(~first).select("doc_id", "row").distinct(), F.col("doc_id").cast("long"), F.xxhash64("text"))
    again = written(groups.where(first).groupBy("doc_id", "row").agg(F.count("*").alias("n")).where("n > 1").select("doc_id", "row"), folder, "again")
    if again.isEmpty():
        return kept
    repeats = docs.join(bounded(again.toDF("__id", "__row")), F.col("doc_id").cast("long").eqNullSafe(F.col("__id")) & (F.xxhash64("text") == F.col("__row")), "left_semi")
    return without(kept, again, F.col("doc_id").cast("long"), F.xxhash64("text")).unionByName(repeats.dropDuplicates(["doc_id", "text"]))


OP8_RULE = JoinRule(width=3, percent=90)


def op8_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), OP8_RULE)


OP8_SQL = r"""
WITH RECURSIVE worded AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents
), sets AS (
  SELECT doc_id, list_sort(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
    ELSE list_distinct(list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2])) END) AS shingles FROM worded
), classes AS (
  SELECT shingles, len(shingles) AS n, min(doc_id) AS class_id FROM sets WHERE len(shingles) > 0 GROUP BY shingles
), items AS (
  SELECT class_id, n, unnest(shingles) AS g FROM classes
), pairs AS (
  SELECT a.class_id AS a, b.class_id AS b, a.n AS n_a, b.n AS n_b, count(*) AS common FROM items a JOIN items b ON a.g = b.g AND a.class_id < b.class_id AND 100 * least(a.n, b.n) >= 90 * greatest(a.n, b.n)
  GROUP BY ALL
), links AS (
  SELECT a, b FROM pairs WHERE 100 * common >= 90 * (n_a + n_b - common)
), both_ways AS (
  SELECT a, b FROM links UNION ALL SELECT b, a FROM links
), reached AS (
  SELECT class_id AS a, class_id AS b FROM classes UNION SELECT r.a, w.b FROM reached r JOIN both_ways w ON w.a = r.b
), roots AS (
  SELECT a AS class_id, min(b) AS root FROM reached GROUP BY a
)
SELECT s.doc_id, CAST(len(s.shingles) AS BIGINT) AS n_shingles, coalesce(r.root, s.doc_id) AS component_id
FROM sets s LEFT JOIN classes c ON s.shingles = c.shingles LEFT JOIN roots r ON r.class_id = c.class_id
"""
