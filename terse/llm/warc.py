"""WARC archives: written by Spark's text writer, read back in splits with boundary-chain verification.

Writing.  A record is one string (header, blank line, HTTP response or its header alone); the writer's line separator is the record's
closing double line break.  Pages with equal payloads share one response record, the others are revisits.

Reading.  The text reader cuts archives at the magic ``WARC/1.1`` line, so large files are read in splits and any store that Spark reads will do.  Each
piece is a candidate record; the magic may as well stand inside a payload.  From its header a candidate knows where its successor must begin.  Tasks
follow these links inside their split and emit, per candidate, its successor and the first offset outside the split.  Offsets of splits
are running sums of their bytes.  Pointer jumping over the split exits, from offset 0 of each file, finds where each split is entered; a walk
from there keeps the true records.  A file whose chain does not end at its last byte is reported as broken.

Payloads that hold the magic are put together from several pieces; where such a payload crosses a split, its file is read once more.

Defined cases: null html is empty; null url is empty; a null page_id is kept and never referred to; repeated rows are records of their own (of
equal payloads those with the smallest id are all responses); an empty table gives no records; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from base64 import b32encode
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from terse.llm.common import bounded, shared_folder, written

# fixed values of the format
MAGIC = b"WARC/1.1\r\n"
CRLF = "\r\n"
GAP = b"\r\n\r\n"
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
DATE = "2024-01-01T00:00:00Z"


def base32(digest_hex: Column) -> Column:
    """Upper-case base32 of a 40-digit hexadecimal string: each 5 digits are 4 characters."""
    digits = "0123456789ABCDEFGHIJKLMNOPQRSTUV"
    parts = [F.lpad(F.conv(F.substring(digest_hex, 1 + 5 * i, 5), 16, 32), 4, "0") for i in range(8)]
    return F.translate(F.concat(*parts), digits, BASE32)


def _safe(url: Column) -> Column:
    for raw, code in (("\r", "%0D"), ("\n", "%0A"), (" ", "%20"), ("<", "%3C"), (">", "%3E")):
        url = F.replace(url, F.lit(raw), F.lit(code))
    return url


def write_archives(pages: DataFrame, path: str, folder: str, min_bytes: int = 0) -> None:
    """Writes a record for each row of pages (page_id, url, html) into WARC files under ``path``.

    Of payloads of at least ``min_bytes`` bytes that are equal, the smallest page_id is the response.
    """
    payload = F.coalesce("html", F.lit(""))
    rows = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), payload.alias("html"), F.sha1(payload.cast("binary")).alias("sha"), F.octet_length(payload).alias("n"))
    known = written(rows.select("page_id", "sha", "n"), folder, "digests")
    first = known.groupBy("sha").agg(F.min("page_id").alias("first"), F.count("*").alias("copies")).where("copies > 1").select("sha", "first")
    again = known.where(F.col("n") >= min_bytes).join(first, "sha").where("page_id <> first").select("page_id", "sha", "first").distinct()
    again = written(again, folder, "revisits")
    joined = rows.join(bounded(again.withColumnRenamed("page_id", "_page").withColumnRenamed("sha", "_sha")), (F.col("page_id") == F.col("_page")) & (F.col("sha") == F.col("_sha")), "left")
    known_id = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(F.col(c).cast("string"), F.lit("none")), F.lit(">"))
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=UTF-8{CRLF}Content-Length: "), F.col("n").cast("string"), F.lit(CRLF * 2))
    block = F.when(F.col("first").isNull(), F.concat(http, F.col("html"))).otherwise(http)
    lines = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.when(F.col("first").isNull(), "response").otherwise("revisit")),
        F.concat(F.lit("WARC-Record-ID: "), known_id("page_id")),
        F.lit(f"WARC-Date: {DATE}"),
        F.concat(F.lit("WARC-Target-URI: <"), _safe(F.col("url")), F.lit(">")),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), base32(F.col("sha"))),
        F.when(F.col("first").isNotNull(), F.concat(F.lit("WARC-Refers-To: "), known_id("first"))),
        F.when(F.col("first").isNotNull(), F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        F.lit("Content-Type: application/http;msgtype=response"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    record = F.concat(F.concat_ws(CRLF, *lines), F.lit(CRLF * 2), block)  # concat_ws leaves nulls out
    joined.select(record.alias("value")).write.mode("overwrite").option("lineSep", CRLF * 2).text(path)


# ---- reading ---------------------------------------------------------------------------------------------------------

CANDIDATE = pa.schema(
    [("file", pa.string()), ("block", pa.int64()), ("at", pa.int64()), ("next", pa.int64()), ("exit", pa.int64()), ("whole", pa.bool_()), ("page_id", pa.int64())]
    + [("uri", pa.string()), ("type", pa.string()), ("refers_to", pa.int64()), ("declared", pa.string()), ("payload_bytes", pa.int64()), ("digest", pa.string()), ("payload", pa.binary())]
)
_DDL = (
    "file string, block bigint, at bigint, next bigint, exit bigint, whole boolean, page_id bigint, uri string, type string, refers_to bigint, declared string, "
    "payload_bytes bigint, digest string, payload binary"
)


def _fields(header: bytes) -> dict[str, str]:
    out = {}
    for line in header.split(b"\r\n"):
        name, _, value = line.partition(b":")
        out.setdefault(name.strip().lower().decode("latin-1"), value.strip().decode("utf-8", "replace"))
    return out


def _page(value: str | None) -> int | None:
    found = re.search(r"urn:page:(-?\d+)", value or "")
    return int(found[1]) if found else None


def _content(fields: dict[str, str], block: bytes, keep: bool) -> dict:
    """What a record's block says of its payload."""
    head, _, body = block.partition(GAP)
    declared = (fields.get("warc-payload-digest") or "").removeprefix("sha1:")
    if fields.get("warc-type") == "revisit":
        return {"payload_bytes": int(_fields(head).get("content-length") or 0), "digest": declared, "payload": None}
    return {"payload_bytes": len(body), "digest": b32encode(hashlib.sha1(body).digest()).decode(), "payload": body if keep else None}


def _split_rows(pieces: list[tuple[int, bytes]], file: str, block: int, total: int, keep: bool) -> list[dict]:
    """Candidates of one split, from its pieces (place, bytes); places count from the split's first piece."""
    rows, after = [], {}
    for k, (place, data) in enumerate(pieces):
        if block == 0 and place == 0 and k == 0:
            continue  # what stands before the first magic of the file
        last = k
        cut = data.find(GAP)
        while cut < 0 and last + 1 < len(pieces) and len(data) < 1 << 20:  # a header line may end like the magic
            last += 1
            data = data + MAGIC + pieces[last][1]
            cut = data.find(GAP)
        if cut < 0:
            continue
        fields = _fields(data[:cut])
        length = fields.get("content-length", "")
        if not length.isdigit():
            continue
        need = cut + 4 + int(length)
        if len(data) < need:  # the magic stands inside the payload: put the pieces together, as far as this split goes
            parts, have = [data], len(data)
            while have < need and last + 1 < len(pieces):
                last += 1
                parts += [MAGIC, pieces[last][1]]
                have += len(MAGIC) + len(pieces[last][1])
            data = b"".join(parts)
        whole = len(data) >= need
        row = {"file": file, "block": block, "at": place - len(MAGIC), "next": place + need + 4, "whole": whole, "page_id": _page(fields.get("warc-record-id")), "uri": fields.get("warc-target-uri", "").strip("<>")}
        row |= {"type": fields.get("warc-type"), "refers_to": _page(fields.get("warc-refers-to")), "declared": (fields.get("warc-payload-digest") or "").removeprefix("sha1:")}
        row |= _content(fields, data[cut + 4 : need], keep) if whole else {"payload_bytes": None, "digest": None, "payload": None}
        rows.append(row)
    for row in reversed(rows):
        row["exit"] = after.get(row["next"], row["next"])
        after[row["at"]] = row["exit"]
    end = {c: None for c in CANDIDATE.names} | {"file": file, "block": block, "at": total, "type": "split"}
    return [*rows, end]


def _scan(keep: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, pieces, total = None, [], 0
        for batch in batches:
            for file, block, value in zip(*(batch.column(c).to_pylist() for c in ("file", "block", "value")), strict=True):
                if (file, block) != now:
                    if now:
                        yield pa.RecordBatch.from_pylist(_split_rows(pieces, *now, total, keep), schema=CANDIDATE)
                    now, pieces, total = (file, block), [], 0
                pieces.append((total, value))
                total += len(value) + len(MAGIC)
        if now:
            yield pa.RecordBatch.from_pylist(_split_rows(pieces, *now, total, keep), schema=CANDIDATE)

    return run


def _raw(spark: SparkSession, path: str) -> DataFrame:
    lines = spark.read.option("lineSep", MAGIC.decode()).text(path)
    return lines.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.col("value").cast("binary").alias("value"))


def _walk(table: pa.Table) -> pa.Table:
    """Of one split's candidates, those on the chain from its entry."""
    at, following, entry = (table.column(c).to_pylist() for c in ("at", "next", "entry"))
    place = {a: i for i, a in enumerate(at)}
    kept = []
    for i in [i for i, e in enumerate(entry) if e]:
        while i is not None and (not kept or kept[-1] != i):
            kept.append(i)
            i = place.get(following[i])
    return table.drop_columns(["entry"]).take(pa.array(sorted(set(kept)), pa.int64()))


def read_archives(spark: SparkSession, path: str, keep_payload: bool = True) -> DataFrame:
    """Records of the archives under ``path``: file, at (offset), page_id, uri, type, refers_to, declared (digest), payload_bytes, digest, payload.

    Raises ValueError if a file's chain of records does not end at its last byte.
    """
    folder = shared_folder(spark)
    found = written(_raw(spark, path).mapInArrow(_scan(keep_payload), _DDL), folder, "candidates")
    splits = found.where("type = 'split'").groupBy("file", "block").agg(F.max("at").alias("bytes"))
    upto = Window.partitionBy("file").orderBy("block")
    bases = written(splits.select("file", "block", (F.sum("bytes").over(upto) - F.col("bytes")).alias("base"), F.sum("bytes").over(Window.partitionBy("file")).alias("sum")), folder, "splits")
    placed = (
        found.where("type <> 'split' or type is null")
        .join(bounded(bases), ["file", "block"])
        .withColumns({c: F.col(c) + F.col("base") for c in ("at", "next", "exit")})
        .drop("base", "sum")
    )
    links = placed.select("file", "at", "exit")
    starts = links.where("at = 0").select("file", "at")
    doors = links.select("file", F.col("exit").alias("at")).unionByName(starts).distinct()
    step = written(links.join(doors, ["file", "at"]), folder, "step-0")
    reached = written(step.where("at = 0").select("file", "at"), folder, "reached-0")
    n, k = -1, 0
    while n != (n := reached.count()):
        k += 1
        ahead = reached.join(step, ["file", "at"]).select("file", F.col("exit").alias("at"))
        far = step.select("file", F.col("at").alias("exit"), F.col("exit").alias("beyond"))
        step = written(step.join(far, ["file", "exit"], "left").select("file", "at", F.coalesce("beyond", "exit").alias("exit")), folder, f"step-{k}")
        reached = written(reached.unionByName(ahead).distinct(), folder, f"reached-{k}")
    # the last piece of a file has no magic behind it
    ends = bases.select("file", (F.col("sum") - len(MAGIC)).alias("at")).distinct().where("at > 0")
    broken = ends.join(reached, ["file", "at"], "left_anti").select("file").limit(5).collect()
    if broken:
        raise ValueError(f"broken record chain in {', '.join(r['file'] for r in broken)}")
    entered = placed.join(reached.withColumn("entry", F.lit(True)), ["file", "at"], "left").select(*CANDIDATE.names, F.coalesce("entry", F.lit(False)).alias("entry"))
    records = written(entered.groupBy("file", "block").applyInArrow(_walk, _DDL), folder, "records")
    cut = records.where("not whole")
    if cut.limit(1).count():
        records = records.where("whole").unionByName(_completed(spark, path, cut, bases, keep_payload))
    return records.drop("block", "next", "exit", "whole")


def _completed(spark: SparkSession, path: str, cut: DataFrame, bases: DataFrame, keep: bool) -> DataFrame:
    """Records whose payload crosses a split: their bytes are gathered from the pieces of their file."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, total = None, 0
        for batch in batches:
            files, blocks = batch.column("file").to_pylist(), batch.column("block").to_pylist()
            places = []
            for file, block, value in zip(files, blocks, batch.column("value"), strict=True):
                if (file, block) != now:
                    now, total = (file, block), 0
                places.append(total)
                total += len(value.as_py()) + len(MAGIC)
            yield pa.RecordBatch.from_arrays([batch.column("file"), batch.column("block"), pa.array(places, pa.int64()), batch.column("value")], names=["file", "block", "place", "value"])

    def gather(table: pa.Table) -> pa.Table:
        rows = table.sort_by("place").to_pylist()
        data = MAGIC.join(r["value"] for r in rows)
        first = {c: rows[0][c] for c in CANDIDATE.names}
        cut_at = data.find(GAP)
        fields = _fields(data[:cut_at])
        block = data[cut_at + 4 : cut_at + 4 + int(fields["content-length"])]
        return pa.Table.from_pylist([first | {"whole": True} | _content(fields, block, keep)], schema=CANDIDATE)

    texts = _raw(spark, path).join(F.broadcast(cut.select("file").distinct()), "file", "left_semi").mapInArrow(pieces, "file string, block bigint, place bigint, value binary")
    texts = texts.join(bases.select("file", "block", "base"), ["file", "block"]).select("file", (F.col("place") + F.col("base")).alias("place"), "value")
    inside = cut.join(texts, "file").where(f"place >= at + {len(MAGIC)} and place < next")
    return inside.groupBy("file", "at").applyInArrow(gather, _DDL)


def op2_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared_folder(spark)
    write_archives(spark.read.parquet(f"{sf_dir}/pages.parquet"), f"{folder}/archives", folder)
    read = read_archives(spark, f"{folder}/archives", keep_payload=False)
    return read.select("page_id", "payload_bytes", F.col("digest").alias("payload_digest"), F.col("type").alias("record_type"), "refers_to")


OP2_SQL = r"""
WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS hex FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY html) AS first FROM p)
SELECT page_id, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes,
  array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + CAST((CAST('0x' || substr(hex, 1 + 5 * (i // 4), 5) AS BIGINT) >> (5 * (3 - i % 4))) & 31 AS BIGINT), 1)), '') AS payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to
FROM f
"""
