"""Mixing sources to target weights by a low-discrepancy schedule of equal-token blocks.

Every source's documents are shuffled (by a hash, anew for each pass), laid on a token line and cut into blocks of
equally many words.  Slots 0, 1, 2 ... of the mix are golden-ratio points on the unit interval; the interval is divided
by the sources' shares, so slots of a source come evenly spaced.  A slot's rank among the slots of its source names the
block it takes.  Joining ranked slots with blocks gives the mix: (slot, source, pass, document, first word, words).

Everything is SQL expressions.  Order statistics are two-level (chunk totals, then inside a chunk), so a source that
holds a third of all rows is spread over many tasks.

Defined cases: a null text has size 0; a null source is a source of its own, sorted last; rows that repeat are each
rows of the mix; an empty table gives no rows; other columns (clashing names too) are ignored by ``mix`` and never
touched by ``source_targets``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from terse.llm.common import bounded, shared_folder, words, written

SOURCE_BOUND = 10_000
"""Sources whose table may be broadcast."""


@dataclass(frozen=True)
class MixPlan:
    """weights: given to the sources in code-point order, repeating; share: words the mix takes, of all words, as (p, q);
    limit: passes over a source at most; block: words in a block; buckets: parts of a source's shuffled line; chunk: slots ranked together."""

    weights: tuple[int, ...] = (3, 1, 2)
    share: tuple[int, int] = (3, 2)
    limit: int = 2
    block: int = 256
    buckets: int = 1024
    chunk: int = 1 << 14
    seed: int = 7


def sized(docs: DataFrame) -> DataFrame:
    """Rows (row, doc_id, source, size): size is the number of words."""
    return docs.select(
        F.monotonically_increasing_id().alias("row"), F.col("doc_id"), F.col("source"), F.size(words(F.col("text"))).cast("long").alias("size")
    )


def source_targets(sizes: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """Per source: sid (rank, nulls last), source_size, weight, target, quota (whole words), lo and hi (its part of the unit interval, in 2**-31).

    Shares go by weight; a source stops at ``limit`` times its size and the excess is shared again by weight.  Sorted by
    size over weight the stopped sources are a prefix, found by one running sum in whole numbers.
    """
    p, q = plan.share
    everyone = Window.partitionBy()
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    weights = F.array(*[F.lit(w).cast("long") for w in plan.weights])
    per = (
        sizes.groupBy("source")
        .agg(F.sum("size").alias("source_size"))
        .withColumn("sid", (F.row_number().over(by_name) - 1).cast("long"))
        .withColumn("weight", F.element_at(weights, (F.col("sid") % len(plan.weights) + 1).cast("int")))
        .withColumn("cap", F.col("source_size") * plan.limit)
        .withColumn("budget", F.sum("source_size").over(everyone) * p)  # in units of 1/q word
    )
    before = Window.orderBy(F.col("cap") / F.col("weight"), "sid").rowsBetween(Window.unboundedPreceding, -1)
    dec = lambda c: F.col(c).cast("decimal(19,0)")
    ranked = (
        per.withColumn("cap_before", F.coalesce(F.sum("cap").over(before), F.lit(0)))
        .withColumn("weight_left", F.sum("weight").over(everyone) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("spare", F.col("budget") - q * F.col("cap_before"))
        .withColumn("stopped", dec("cap") * q * dec("weight_left") <= dec("weight") * dec("spare"))
    )
    total = (
        ranked.withColumn("cap_all", F.coalesce(F.sum(F.when(F.col("stopped"), F.col("cap"))).over(everyone), F.lit(0)))
        .withColumn("weight_all", F.sum(F.when(~F.col("stopped"), F.col("weight"))).over(everyone))
        .withColumn(
            "target",
            F.when(F.col("stopped"), F.col("cap").cast("double")).otherwise(
                (F.col("weight") * (F.col("budget") - q * F.col("cap_all"))).cast("double") / (F.col("weight_all") * q).cast("double")
            ),
        )
        .withColumn("quota", F.floor(F.col("target") + 0.5).cast("long"))
        .withColumn("quotas", F.sum("quota").over(everyone))
    )
    line = Window.orderBy("sid").rowsBetween(Window.unboundedPreceding, 0)
    return (
        total.withColumn("upto", F.sum("quota").over(line))
        .withColumn("hi", F.when(F.col("quotas") > 0, F.floor(F.col("upto").cast("double") / F.col("quotas") * (1 << 31))).otherwise(0).cast("long"))
        .withColumn("lo", F.coalesce(F.lag("hi").over(Window.orderBy("sid")), F.lit(0).cast("long")))
        .select("sid", "source", "source_size", "weight", "target", "quota", "lo", "hi")
    )


def slots(targets: DataFrame, n_slots: int, plan: MixPlan = MixPlan()) -> DataFrame:
    """Slots (slot, sid, rank): golden-ratio points mapped through the cumulative shares and ranked within their source.

    The unit interval is cut into 4,096 cells; a slot meets, by an equality join, only the sources that touch its cell.  Each source gets exactly
    as many slots as its quota has blocks: surplus ones are left out, missing ones (a handful, by the discrepancy) come last.
    """
    spark = targets.sparkSession
    need = F.ceil(F.col("quota") / plan.block).cast("long")
    cells = targets.where("hi > lo").select("sid", "lo", "hi", F.explode(F.sequence(F.shiftright("lo", 19), F.shiftright(F.col("hi") - 1, 19))).alias("cell"))
    points = spark.range(n_slots).select(
        F.col("id").alias("slot"), F.pmod(F.pmod("id", F.lit(1 << 31)) * F.lit(1327217885), F.lit(1 << 31)).alias("point")
    ).withColumn("cell", F.shiftright("point", 19))
    hit = points.join(bounded(cells, 2 * SOURCE_BOUND), "cell").where("point >= lo and point < hi").select("slot", "sid", F.expr(f"slot div {plan.chunk}").alias("chunk"))
    counts = hit.groupBy("sid", "chunk").agg(F.count("*").alias("n"))
    order = Window.partitionBy("sid").orderBy("chunk")
    starts = counts.select("sid", "chunk", (F.sum("n").over(order) - F.col("n")).alias("start"))
    inside = Window.partitionBy("sid", "chunk").orderBy("slot")
    ranked = hit.withColumn("in_chunk", F.row_number().over(inside) - 1).join(starts, ["sid", "chunk"]).select("slot", "sid", (F.col("start") + F.col("in_chunk")).alias("rank"))
    kept = ranked.join(bounded(targets.select("sid", need.alias("need")), SOURCE_BOUND), "sid").where("rank < need").select("slot", "sid", "rank")
    have = counts.groupBy("sid").agg(F.sum("n").alias("have"))
    missing = (
        targets.select("sid", need.alias("need"))
        .join(have, "sid", "left")
        .where("need > coalesce(have, 0)")
        .select("sid", F.explode(F.expr("sequence(coalesce(have, 0L), need - 1)")).alias("rank"))
        .select((F.lit(n_slots) + F.row_number().over(Window.orderBy("rank", "sid")) - 1).cast("long").alias("slot"), "sid", "rank")
    )
    return kept.unionByName(missing)


def segments(sizes: DataFrame, targets: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """Documents cut along their source's shuffled line: (sid, rank, epoch, row, doc_id, first_word, n_words), rank the block's number."""
    known = bounded(targets.select("sid", F.col("source").alias("its_source"), "source_size", "quota"), SOURCE_BOUND)
    rows = (
        sizes.where("size > 0")
        .join(known, F.col("source").eqNullSafe(F.col("its_source")))
        .select("row", "doc_id", "size", "sid", "source_size", "quota", F.explode(F.sequence(F.lit(0), F.lit(plan.limit - 1))).alias("epoch"))
        .where("epoch * source_size < quota")
        .withColumn("key", F.md5(F.concat_ws(":", F.lit(plan.seed), "epoch", F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary")))
        .withColumn("bucket", F.conv(F.substring("key", 1, 8), 16, 10).cast("long") % plan.buckets)
    )
    totals = rows.groupBy("sid", "epoch", "bucket").agg(F.sum("size").alias("n"))
    order = Window.partitionBy("sid", "epoch").orderBy("bucket")
    bases = totals.select("sid", "epoch", "bucket", (F.sum("n").over(order) - F.col("n")).alias("base"))
    inside = Window.partitionBy("sid", "epoch", "bucket").orderBy("key", "size", "row").rowsBetween(Window.unboundedPreceding, 0)
    placed = (
        rows.withColumn("upto", F.sum("size").over(inside))
        .join(bases, ["sid", "epoch", "bucket"])
        .withColumn("start", F.col("epoch") * F.col("source_size") + F.col("base") + F.col("upto") - F.col("size"))
        .where("start < quota")
        .withColumn("stop", F.least(F.col("start") + F.col("size"), F.col("quota")))
    )
    return (
        placed.withColumn("rank", F.explode(F.expr(f"sequence(start div {plan.block}, (stop - 1) div {plan.block})")))
        .withColumn("from", F.greatest("start", F.col("rank") * plan.block))
        .withColumn("to", F.least("stop", (F.col("rank") + 1) * plan.block))
        .select("sid", "rank", "epoch", "row", "doc_id", (F.col("from") - F.col("start")).alias("first_word"), (F.col("to") - F.col("from")).alias("n_words"))
    )


def mix(docs: DataFrame, plan: MixPlan = MixPlan()) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(mix, sizes, targets): the mix in slots with pieces of documents, the sized rows, and the sources with their targets."""
    folder = shared_folder(docs.sparkSession)
    sizes = written(sized(docs), folder, "sizes")
    targets = written(source_targets(sizes, plan).coalesce(1), folder, "targets")
    n_slots = targets.agg(F.coalesce(F.sum(F.ceil(F.col("quota") / plan.block)), F.lit(0)).cast("long")).first()[0]
    taken = slots(targets, n_slots, plan).join(segments(sizes, targets, plan), ["sid", "rank"])
    return taken.select("slot", "sid", "epoch", "row", "doc_id", "first_word", "n_words"), sizes, targets


def mix_digest(docs: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """Per document row: doc_id, source, size, source_size, target and taken, the words that the mix takes of it."""
    pieces, sizes, targets = mix(docs, plan)
    used = pieces.groupBy("row").agg(F.sum("n_words").alias("taken"))
    known = bounded(targets.select(F.col("source").alias("its_source"), "source_size", "target"), SOURCE_BOUND)
    return (
        sizes.join(known, F.col("source").eqNullSafe(F.col("its_source")))
        .join(used, "row", "left")
        .select("doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))
    )


def op1_query(spark, sf_dir: str) -> DataFrame:
    return mix_digest(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("source")


# The same mix in SQL: the quota of every source is taken from the front of its shuffled line, so no slot table is needed.
OP1_SQL = r"""
WITH sizes AS (
  SELECT doc_id, source, CAST(len(list_filter(regexp_split_to_array(coalesce(text, ''), '[ \t\n\x0B\f\r]+'), lambda w: w <> '')) AS BIGINT) AS size FROM documents
), per AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY source ASC NULLS LAST) - 1 AS sid FROM sizes GROUP BY source
), weighed AS (
  SELECT *, CASE sid % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END AS weight, 2 * source_size AS cap, CAST(3 * sum(source_size) OVER () AS BIGINT) AS budget FROM per
), ranked AS (
  SELECT *, coalesce(sum(cap) OVER w, 0) AS cap_before, sum(weight) OVER () - coalesce(sum(weight) OVER w, 0) AS weight_left FROM weighed
  WINDOW w AS (ORDER BY cap / weight, sid ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
), marked AS (
  SELECT *, 2 * cap * weight_left <= weight * (budget - 2 * cap_before) AS stopped FROM ranked
), aimed AS (
  SELECT source, sid, source_size, CASE WHEN stopped THEN CAST(cap AS DOUBLE) ELSE
    CAST(CAST(weight * (budget - 2 * coalesce(sum(CASE WHEN stopped THEN cap END) OVER (), 0)) AS BIGINT) AS DOUBLE) / CAST(CAST(2 * sum(CASE WHEN NOT stopped THEN weight END) OVER () AS BIGINT) AS DOUBLE) END AS target
  FROM marked
), passes AS (
  SELECT s.doc_id, s.size, a.sid, a.source_size, CAST(floor(a.target + 0.5) AS BIGINT) AS quota, e.epoch, md5('7:' || e.epoch || ':' || coalesce(CAST(s.doc_id AS VARCHAR), '')) AS key
  FROM sizes s JOIN aimed a ON s.source IS NOT DISTINCT FROM a.source, (VALUES (0), (1)) e(epoch)
), placed AS (
  SELECT doc_id, size, quota, epoch * source_size + sum(size) OVER (PARTITION BY sid, epoch ORDER BY CAST(('0x' || substr(key, 1, 8)) AS BIGINT) % 1024, key, size ROWS UNBOUNDED PRECEDING) - size AS start FROM passes
), used AS (
  SELECT doc_id, CAST(sum(greatest(0, least(start + size, quota) - start)) AS BIGINT) AS taken FROM placed GROUP BY doc_id
)
SELECT s.doc_id, s.size, a.source_size, a.target, u.taken FROM sizes s JOIN aimed a ON s.source IS NOT DISTINCT FROM a.source JOIN used u USING (doc_id)
"""
