from __future__ import annotations

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from terse import catalogue

SAMPLE = [n for k, n in enumerate(sorted(catalogue.SQL)) if k % 6 == 0] + ["iter3_two_way", "iter3_two_sided", "codec_ternary_inf", "stream_session", "stream_interval_join", "stream_dedupe_watermark", "feat_allocate_even"]


@pytest.mark.parametrize("name", sorted(set(SAMPLE)))
def test_query_equals_sql(spark, duck, equal_rows, sf_dir, name):
    equal_rows(catalogue.QUERIES[name](spark, sf_dir).toPandas(), duck.sql(catalogue.SQL[name]).df())


def test_entry(spark):
    import __spark_entry__ as entry

    rows = entry.entry(spark).toPandas()
    for _, run in rows.groupby("method"):
        assert run.loss.iloc[-1] < run.loss.iloc[0]
    assert set(catalogue.QUERIES) <= set(entry.queries()) and set(catalogue.SQL) <= set(entry.oracle_sql())


def test_message_source(spark):
    from terse.sources.tables import MessageSource

    spark.dataSource.register(MessageSource)
    rows = spark.read.format("terse_messages").option("workers", 3).load().collect()
    assert sorted(r["sender"] for r in rows) == [0, 1, 2] and all(len(r["payload"]) == 4 * 4 + 13 for r in rows)


def test_formats_round_trip(spark, sf_dir, tmp_path):
    from terse.sources.tables import FORMATS, read, require, round_trip

    nation = read(spark, sf_dir, "nation")
    for kind in FORMATS:
        assert sorted(round_trip(nation, f"file://{tmp_path}", kind).collect()) == sorted(nation.collect())
    with pytest.raises(TypeError):
        require(nation, "n_name int")


def test_text_and_whole_files(spark, tmp_path):
    from terse.sources.tables import text_lines, whole_files

    (tmp_path / "a.txt").write_text("one\ntwo\n")
    (tmp_path / "b.bin").write_bytes(b"\x00\xff")
    assert sorted(r["value"] for r in text_lines(spark, f"file://{tmp_path}/a.txt").collect()) == ["one", "two"]
    (found,) = whole_files(spark, f"file://{tmp_path}", "*.bin").collect()
    assert found["length"] == 2 and bytes(found["content"]) == b"\x00\xff"


def test_training_on_a_stream_goes_on_after_a_stop(spark, sf_dir, tmp_path):
    from terse.sources.tables import SCHEMAS, read
    from terse.streaming.online import train

    rows, kinds = read(spark, sf_dir, "events"), sorted(r[0] for r in read(spark, sf_dir, "events", "event_type").distinct().collect())
    stream = lambda path: spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", 1).parquet(path)
    part = lambda k, path: rows.where(rows.event_id % 3 == k).coalesce(1).write.mode("append").parquet(path)
    whole, halves = f"file://{tmp_path}/whole", f"file://{tmp_path}/halves"
    for k in range(3):
        part(k, whole)
    part(0, halves)
    once = train(spark, stream(whole), kinds, f"file://{tmp_path}/w1")
    first = train(spark, stream(halves), kinds, f"file://{tmp_path}/w2")
    for k in (1, 2):
        part(k, halves)
    assert first + train(spark, stream(halves), kinds, f"file://{tmp_path}/w2") == once and len(once) == 3


def test_pruning_and_broadcast_show_in_plans(spark, sf_dir):
    plan = catalogue.QUERIES["scan_pruned"](spark, sf_dir)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull" in plan and "l_extendedprice" not in plan.split("== Physical Plan ==")[1]
    assert "BroadcastHashJoin" in catalogue.QUERIES["join_broadcast"](spark, sf_dir)._jdf.queryExecution().toString()


def test_sketches_stay_near_exact_values(spark, duck, sf_dir):
    exact = {r[0]: r[1:] for r in duck.sql("select l_returnflag, count(distinct l_orderkey), median(l_extendedprice), count(*) from lineitem group by 1").fetchall()}
    for r in catalogue.QUERIES["agg_sketch"](spark, sf_dir).collect():
        orders, price, rows = exact[r["l_returnflag"]]
        assert abs(r["orders"] - orders) <= 0.1 * orders and abs(r["prices"][1] - price) <= 0.05 * price
        assert sum(b["y"] for b in r["quantities"]) == rows


def test_progress_is_told(spark, sf_dir):
    from terse.streaming.online import Progress

    heard = Progress()
    spark.streams.addListener(heard)
    try:
        catalogue.QUERIES["stream_dedupe"](spark, sf_dir).count()
        for _ in range(50):
            if heard.batches:
                break
            time.sleep(0.2)
    finally:
        spark.streams.removeListener(heard)
    assert sum(b[2] for b in heard.batches) == spark.read.parquet(f"{sf_dir}/events.parquet").count()


@pytest.mark.parametrize("name", ["stream_dedupe_watermark", "stream_session"])
def test_streams_end_in_files(spark, sf_dir, name):
    assert catalogue.QUERIES[name](spark, sf_dir).inputFiles()  # nothing is held by the driver


def _odd_events(spark, path: str) -> str:
    """Of four files by event_id modulo 4: gaps of 6 hours and a microsecond less, a time that joins two sessions of earlier files, rows without a user or a time, and a
    user with more rows than Python gets at once."""
    from datetime import datetime, timedelta

    at = lambda h, micros=0: datetime(1969, 12, 31, 20) + timedelta(hours=h, microseconds=micros)
    rows = [(0, at(0), 1), (4, at(6), 1), (8, at(12, -1), 1), (12, at(12, -1), 1)]
    rows += [(16, at(0), 2), (20, at(10), 2), (21, at(5), 2), (24, at(30), 2), (25, at(29), 2), (26, at(31), 2), (27, at(36, 1), 2)]
    rows += [(28, None, 3), (29, None, 3), (30, at(1), 3), (31, None, 3), (32, at(0), None), (33, at(5), None), (34, None, None), (36, None, None), (40, at(2), 0), (41, at(2), 2**53 + 1), (42, at(2), 2**53)]
    few = spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long")
    many = spark.range(0, 100_000, 4, 1).select(F.col("id").alias("event_id"), F.expr("timestamp_ntz'2024-03-01' + make_dt_interval(0, id div 4000 * 6, 0, id % 4000 / 1000)").alias("ts"), F.lit(-5).cast("long").alias("user_id"))
    whole = few.union(many).withColumns({"event_type": F.lit("view"), "value": F.lit(1.0), "props": F.lit("{}")})
    whole.coalesce(1).write.parquet(f"file://{path}/events.parquet")
    return f"file://{path}"


def test_sessions_of_odd_events_need_no_state_store(spark, equal_rows, tmp_path):
    from pathlib import Path
    from urllib.parse import urlparse

    import duckdb

    from terse.streaming.online import _raw, _trickled, sessions

    odd = _odd_events(spark, str(tmp_path))
    con = duckdb.connect()
    con.sql(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    want = con.sql(catalogue.SQL["stream_session"]).df()
    found = catalogue.QUERIES["stream_session"](spark, odd)
    equal_rows(found.toPandas(), want)
    folder = next(p for p in Path(urlparse(found.inputFiles()[0]).path).parents if p.name.startswith("terse-"))
    assert (folder / "stream" / "offsets").exists() and not (folder / "stream" / "state").exists()
    for k, stream in ((4, _trickled(spark, odd)), (1, _raw(spark, odd))):
        table = sessions(stream, 6)
        assert {f"/sessions/{k - 1}/" in p for p in table.inputFiles()} == {True}
        equal_rows(table.select("user_id", F.date_format("first", "yyyy-MM-dd HH:mm:ss").alias("start"), "n").toPandas(), want)
    assert sessions(_raw(spark, odd).where("false"), 6).count() == 0


def test_drained_tables_of_several_batches(spark, sf_dir):
    from terse.streaming.online import _trickled, drained, events

    want = {r["event_type"]: r["count"] for r in spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("event_type").count().collect()}
    by_type = lambda rows: {r["event_type"]: r["count"] for r in rows}
    whole = drained(_trickled(spark, sf_dir).groupBy("event_type").count(), "complete").collect()
    assert len(whole) == len(want) and by_type(whole) == want
    rows = drained(_trickled(spark, sf_dir), "append")
    assert rows.count() == sum(want.values()) and by_type(rows.groupBy("event_type").count().collect()) == want
    nothing = drained(events(spark, sf_dir).where("false"), "append")
    assert nothing.count() == 0 and "event_id" in nothing.columns


BITS = ["bits_message_edges", "bits_per_iteration", "bits_rate", "bits_raw", "bits_saving", "bits_ternary"]


@pytest.mark.parametrize("name", BITS)
def test_bits_are_of_the_vectors_given(spark, equal_rows, tmp_path, name):
    import duckdb

    sizes = {-3: 7, 0: 64, 7: 500, 10: 0, 25: None, 40: 321}
    rows = [(i, None if n is None else [0.5] * n, 0) for i, n in sizes.items()]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"file://{tmp_path}/embeddings.parquet")
    con = duckdb.connect()
    con.sql(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    found = catalogue.QUERIES[name](spark, f"file://{tmp_path}").toPandas()
    equal_rows(found, con.sql(catalogue.SQL[name]).df())
    if name == "bits_message_edges":  # ids -3, 0, 7, 40 by 2: 1 and 0; by 5: 2 and 0; by 10: 7 and 0; by 20: 17, 0 and 7
        assert {(r.topology, r.workers): r.messages for r in found.itertuples()} == {("star", n): 2 * k for n, k in ((2, 2), (5, 2), (10, 2), (20, 3))} | {("all_to_all", n): k for n, k in ((2, 2), (5, 2), (10, 2), (20, 6))}
    else:
        assert set(zip(found.vec_id, found.d, strict=True)) == {(i, n) for i, n in sizes.items() if n}
        assert len(found) == 4 * {"bits_raw": 1, "bits_ternary": 6, "bits_rate": 6}.get(name, 42)


def test_bias_covers_all_vectors(spark, sf_dir):
    from terse.functions.draws import draw

    rows = catalogue.QUERIES["codec_bias"](spark, sf_dir).toPandas()
    vectors = {r["vec_id"]: np.floor(np.asarray(r["embedding"], float) * 2**20 + 0.5).astype(int) for r in spark.read.parquet(f"{sf_dir}/embeddings.parquet").collect()}
    assert len(vectors) > 20 and len(rows) == sum(map(len, vectors.values()))
    assert set(zip(rows.vec_id, rows.coord, rows.v, strict=True)) == {(i, c, x) for i, e in vectors.items() for c, x in enumerate(e.tolist())}
    last = max(vectors)
    keys = spark.range(len(vectors[last])).select(F.lit(last).alias("vec_id"), F.col("id").alias("coord")).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(15))))
    drawn = keys.withColumn("u", draw(32, F.col("vec_id"), F.col("coord"), F.col("rep"), mode="portable")).toPandas()
    total = dict.fromkeys(range(len(vectors[last])), 0)
    for c, u in zip(drawn.coord, drawn.u, strict=True):
        scale = max(abs(x) for x in vectors[last][c // 16 * 16 : c // 16 * 16 + 16])
        total[c] += int(np.sign(vectors[last][c]) * scale) if u * scale < abs(vectors[last][c]) else 0
    mine = rows[rows.vec_id == last]
    assert dict(zip(mine.coord, mine.total, strict=True)) == total


def test_gram_covers_all_coordinates(spark, sf_dir):
    rows = catalogue.QUERIES["measure_gram"](spark, sf_dir).toPandas()
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").toPandas().embedding
    x = np.floor(np.stack(vectors).astype(float) * 2**20 + 0.5).astype(int).astype(object)
    want = x.T @ x
    assert len(rows) == want.shape[0] * (want.shape[0] + 1) // 2
    assert all(want[r.i, r.j] == r.g and r.i <= r.j for r in rows.itertuples())
