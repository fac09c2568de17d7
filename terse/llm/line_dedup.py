"""Cross-site boilerplate lines found by distinct-site spread, and their removal.

A line is known by a 64-bit hash of its trimmed text.  For every line seen on two sites or more, a HyperLogLog sketch of its sites is
built by aggregation and merged.  Where an estimate lies near its threshold, an exact distinct count decides.  A line is *spread* if it has enough words and is
on enough sites (shorter lines need more); the number of its sites alone decides that.

Copies.  Lines of a document copied to many sites are spread as well, yet no boilerplate.  What tells them apart is the document: of its judged lines (those with
words enough), let ``own`` be how often the line a ``share``-th from the rarest on stands in the corpus, 0 for lines that are not spread; where there are fewer
lines than that, how many documents have the same judged lines.  A spread line goes if it stands ``times`` that often or more.  So where more than a
share of the lines are the document's own, all spread lines go, and of a copy go those that are much commoner than the copy itself; removing copies is the
task of another operator.

SQL expressions only.  Only hashes are shuffled, merged by task before; texts stay where they were read unless the lines to remove are too
many to be broadcast, which is measured.

Defined cases: null text stays null; a null source is a site of its own; rows that repeat are treated alike; lines without a word are
kept as they are; a document whose lines all go has an empty text; an empty table stays empty; all other columns pass through, but for n_lines and n_removed,
which replace columns of these names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from terse.llm.common import BLANK_CHARS, BLANK_CLASS, bounded, shared_folder, small, written


@dataclass(frozen=True)
class SpreadRule:
    """A line of w words needs greatest(min_sites, ceil(spread / w)) sites and min_words words; share, times: what tells boilerplate from copies; sketch:
    logarithm of its registers; salts: parts that the occurrences of a line are dealt into where they are joined by shuffle; entries: of lines to remove that may be broadcast."""

    min_words: int = 3
    min_sites: int = 4
    spread: int = 24
    share: int = 5
    times: int = 2
    sketch: int = 12
    salts: int = 16
    entries: int = 4_000_000


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n")


def _line_hash(line: Column) -> Column:
    return F.xxhash64(F.trim(line, F.lit(BLANK_CHARS)))


def row_key(doc_id: Column, text: Column) -> Column:
    return F.xxhash64(doc_id, text)


def occurrences(docs: DataFrame, rule: SpreadRule) -> DataFrame:
    """(key, line, need, site, place, lines, body): a row for each line with enough words; how many there are in the document and their hash."""
    hashed = docs.select(
        row_key(F.col("doc_id"), F.col("text")).alias("key"),
        F.xxhash64(F.col("source").isNull(), F.col("source")).alias("site"),
        F.transform(_lines(F.col("text")), lambda x: F.struct(_line_hash(x).alias("h"), F.size(F.filter(F.split(x, BLANK_CLASS), lambda w: w != "")).alias("w"))).alias("l"),
    )
    judged = hashed.withColumn("l", F.filter("l", lambda x: x["w"] >= rule.min_words))
    judged = judged.withColumn("body", F.xxhash64(F.transform("l", lambda x: x["h"])))
    return judged.select("key", "site", F.size("l").alias("lines"), "body", F.posexplode("l").alias("place", "x")).select(
        "key", F.col("x.h").alias("line"), F.greatest(F.lit(rule.min_sites), F.ceil(F.lit(rule.spread) / F.col("x.w"))).cast("int").alias("need"), "site", "place", "lines", "body"
    )


def spread_lines(occ: DataFrame, rule: SpreadRule, folder: str) -> DataFrame:
    """(line, n): the spread lines among written occurrences, and how often each stands there."""
    seen = occ.groupBy("line").agg(F.min("site").alias("s0"), F.max("site").alias("s1"), F.count("*").alias("n"), F.max("need").alias("need"))
    seen = written(seen.where("s0 <> s1 and n >= need").select("line", "n", "need"), folder, "seen")
    if small(seen):
        wide = occ.select("line", "site").join(F.broadcast(seen), "line")
    else:  # a hot line has no more rows than sites before it is joined
        wide = occ.groupBy("line", "site").agg(F.lit(1).alias("x")).drop("x").join(seen, "line")
    sketches = wide.groupBy("line").agg(F.first("n").alias("n"), F.first("need").alias("need"), F.hll_sketch_estimate(F.hll_sketch_agg("site", F.lit(rule.sketch))).alias("sites"))
    near = F.abs(F.col("sites") - F.col("need")) <= F.greatest(F.lit(1.0), F.col("need") * 0.1)
    judged = written(sketches.withColumn("near", near).where(F.col("near") | (F.col("sites") >= F.col("need"))), folder, "judged")
    sure = judged.where("not near").select("line", "n")
    close = judged.where("near").select("line")
    # distinct sites are counted in two steps, so that a hot line is counted by many tasks
    exact = wide.join(bounded(close), "line", "left_semi").groupBy("line", "n", "need", "site").agg(F.lit(1).alias("x")).groupBy("line", "n", "need").agg(F.count("*").alias("sites"))
    return sure.unionByName(exact.where("sites >= need").select("line", "n"))


def _joined(many: DataFrame, few: DataFrame, on: str, rule: SpreadRule, how: str = "inner") -> DataFrame:
    """Rows of many (with key) joined with written rows of few; by shuffle, what is equal is dealt into salts."""
    if small(few):
        return many.join(F.broadcast(few), on, how)
    salted = few.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(rule.salts - 1))))
    return many.withColumn("salt", F.pmod("key", F.lit(rule.salts)).cast("int")).join(salted, [on, "salt"], how).drop("salt")


def boilerplate(occ: DataFrame, spread: DataFrame, rule: SpreadRule, folder: str) -> DataFrame:
    """(key, gone): by document the hashes of the lines to remove."""
    copies = occ.where((F.col("place") == 0) & (F.col("lines") < rule.share)).groupBy("body").agg(F.count("*").alias("copies")).where("copies > 1")
    met = _joined(occ.select("key", "line"), spread, "line", rule).groupBy("key").agg(F.sort_array(F.collect_list(F.struct("n", "line"))).alias("met"))
    total = occ.groupBy("key").agg(F.count("*").alias("judged"), F.first("lines").alias("lines"), F.first("body").alias("body"))
    both = _joined(written(total.join(met, "key"), folder, "met"), written(copies, folder, "copies"), "body", rule, "left")
    place = F.floor(F.col("judged") / rule.share).cast("int") - (F.col("judged") - F.size("met")).cast("int")  # among the spread lines
    own = F.when(F.col("lines") < rule.share, F.coalesce("copies", F.lit(1))).when(place >= 0, F.get("met", place)["n"]).otherwise(0)
    gone = F.array_distinct(F.transform(F.filter("met", lambda x: x["n"] >= rule.times * F.col("own")), lambda x: x["line"]))
    return both.withColumn("own", own).select("key", gone.alias("gone")).where(F.size("gone") > 0)


def dedup_lines(docs: DataFrame, rule: SpreadRule = SpreadRule()) -> DataFrame:
    """The documents without boilerplate lines, with n_lines (lines with a word) and n_removed added."""
    folder = shared_folder(docs.sparkSession)
    occ = written(occurrences(docs, rule), folder, "occurrences")
    spread = written(spread_lines(occ, rule, folder), folder, "spread")
    hit = written(boilerplate(occ, spread, rule, folder).toDF("__key", "__gone"), folder, "touched")
    entries = hit.agg(F.coalesce(F.sum(F.size("__gone") + 2), F.lit(0))).first()[0]
    lines = _lines(F.col("__text"))
    filled = lambda x: F.size(F.filter(x, lambda y: F.trim(y, F.lit(BLANK_CHARS)) != "")).cast("long")
    keyed = docs.withColumnsRenamed({"text": "__text"}).withColumn("__row", row_key(F.col("doc_id"), F.col("__text")))
    joined = keyed.join(F.broadcast(hit) if entries <= rule.entries else hit, F.col("__row") == F.col("__key"), "left")
    kept = F.when(F.col("__gone").isNull(), F.col("__text")).otherwise(F.array_join(F.filter(lines, lambda x: ~F.array_contains("__gone", _line_hash(x))), "\n"))
    return (
        joined.withColumn("text", kept)
        .withColumn("n_lines", filled(lines))
        .withColumn("n_removed", F.col("n_lines") - filled(_lines(F.col("text"))))
        .select(*[c for c in docs.columns if c not in ("n_lines", "n_removed")], "n_lines", "n_removed")
    )


def op9_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = dedup_lines(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return done.select("doc_id", "n_lines", "n_removed", F.char_length("text").cast("long").alias("clean_chars"), F.md5(F.col("text").cast("binary")).alias("clean_md5"))


def dedup_sql(table: str = "documents") -> str:
    """DuckDB SQL for the cleaned rows of a table with doc_id, text, lang, source, n_chars: exact counts in place of sketches."""
    trimmed = "trim(x, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13))"
    return rf"""
  SELECT d.doc_id, CASE WHEN g.gone IS NULL THEN d.text ELSE array_to_string(list_filter(string_split(d.text, chr(10)), lambda x: NOT list_contains(g.gone, {trimmed})), chr(10)) END AS text,
    d.lang, d.source, d.n_chars, d.text AS whole
  FROM {table} d LEFT JOIN (
    WITH bodies AS (
      SELECT doc_id, text, coalesce('s' || source, 'n') AS site,
        list_filter(list_transform(string_split(coalesce(text, ''), chr(10)), lambda x: {trimmed}), lambda x: x <> '' AND len(regexp_split_to_array(x, '[ \t\n\x0B\f\r]+')) >= 3) AS body
      FROM {table}
    ), lines AS (
      SELECT doc_id, text, site, body, unnest(body) AS line FROM bodies
    ), spread AS (
      SELECT line, count(*) AS n FROM lines GROUP BY line HAVING count(DISTINCT site) >= greatest(4, ceil(24.0 / len(regexp_split_to_array(line, '[ \t\n\x0B\f\r]+'))))
    ), copies AS (
      SELECT body, count(*) AS copies FROM bodies GROUP BY body
    ), judged AS (
      SELECT doc_id, text, body, list(coalesce(n, 0) ORDER BY coalesce(n, 0)) AS counts, list(struct_pack(n := n, line := l.line)) FILTER (n IS NOT NULL) AS met
      FROM lines l LEFT JOIN spread s ON l.line = s.line GROUP BY doc_id, text, body
    )
    SELECT doc_id, text, list_transform(list_filter(met, lambda x: x.n >= 2 * CASE WHEN len(body) < 5 THEN copies ELSE counts[len(counts) // 5 + 1] END), lambda x: x.line) AS gone
    FROM judged JOIN copies USING (body) WHERE met IS NOT NULL
  ) g ON g.doc_id IS NOT DISTINCT FROM d.doc_id AND g.text = d.text"""


OP9_SQL = f"""
SELECT doc_id, CAST(len(list_filter(string_split(coalesce(whole, ''), chr(10)), lambda x: NOT regexp_full_match(x, '[ \\t\\n\\x0B\\f\\r]*'))) AS BIGINT) AS n_lines,
  CAST(len(list_filter(string_split(coalesce(whole, ''), chr(10)), lambda x: NOT regexp_full_match(x, '[ \\t\\n\\x0B\\f\\r]*'))) - len(list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: NOT regexp_full_match(x, '[ \\t\\n\\x0B\\f\\r]*'))) AS BIGINT) AS n_removed,
  length(text) AS clean_chars, md5(text) AS clean_md5
FROM ({dedup_sql()})
"""
