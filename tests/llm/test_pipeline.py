from __future__ import annotations

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from terse.llm import line_dedup, nearest_toxic
from terse.llm.common import held_out


def grams(text, n=5):
    words = (text or "").lower().split()
    return {tuple(words[i : i + n]) for i in range(len(words) - n + 1)} if len(words) >= n else ({tuple(words)} if words else set())


@pytest.fixture(scope="module")
def stages(spark, sf_dir):
    """Rows after each stage, by name."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = [("documents", docs.toPandas())]
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf_dir).persist()
        out.append((name, docs.toPandas()))
    return out


def test_each_stage_against_brute_force(spark, sf_dir, duck, stages):
    rows = dict(stages)
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    score = nearest_toxic.score(docs, nearest_toxic.fit(docs, labels, ~held_out(F.col("doc_id"), 5, 0))).toPandas()
    assert set(rows["toxicity"].doc_id) == set(score.doc_id[score.score < 0.5])
    kept = rows["toxicity"]
    duck.register("kept", kept)
    want = duck.sql(line_dedup.dedup_sql("kept")).df().set_index("doc_id").text.to_dict()
    assert rows["line_dedup"].set_index("doc_id").text.to_dict() == want
    texts = rows["line_dedup"].sort_values("doc_id")
    sets = [(d, grams(t)) for d, t in zip(texts.doc_id, texts.text, strict=True)]
    root = {d: d for d, _ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (a, x) in enumerate(sets):
        for b, y in sets[:i]:
            if x and y and 100 * len(x & y) >= 80 * len(x | y):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    assert set(rows["near_duplicates"].doc_id) == {d for d in root if find(d) == d}
    items = [t for t in duck.sql("select text from benchmark").df().text]
    whole = {d for d, t in zip(rows["near_duplicates"].doc_id, rows["near_duplicates"].text, strict=True) if any(i in (t or "") for i in items)}
    after = set(rows["decontamination"].doc_id)
    assert not after & whole
    assert len(set(rows["near_duplicates"].doc_id) - after - whole) <= 1
    mixed = rows["mix"]
    assert set(mixed.doc_id) == after and (mixed.taken <= 2 * mixed["size"]).all()
    columns = list(rows["documents"].columns)
    assert all(list(r.columns) == columns for n, r in stages if n != "mix")


def test_run_gives_the_last_stage(spark, sf_dir, stages):
    last = stages[-1][1]
    again = corpus_pipeline.run(spark, sf_dir).toPandas()
    key = ["doc_id", "size", "taken"]
    assert again[key].sort_values(key).reset_index(drop=True).equals(last[key].sort_values(key).reset_index(drop=True))
