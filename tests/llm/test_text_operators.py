from __future__ import annotations

import math
import random
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from terse.llm import chat_format, decontaminate, kneser_ney, line_dedup, nearest_toxic, quality_rules, registry, shingle_join, source_mix, subword_quality, warc
from terse.llm import text_kernel as kernel

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_lines bigint, size string"


def docs_of(spark, texts, sources=None, ids=None):
    """Documents with extra columns whose names clash with those of the operators."""
    sources = sources or [f"s{i % 5}" for i in range(len(texts))]
    ids = ids or list(range(len(texts)))
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t), 7, "x") for i, t, s in zip(ids, texts, sources, strict=True)], DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and blank texts, ties, repeated rows, and one long text."""
    rng = random.Random(1)
    long = " ".join(rng.choice("alpha beta gamma delta epsilon".split()) + str(rng.randrange(50)) for _ in range(30_000))
    texts = [None, "", " \n\t ", "one", "one", "two words", long, "a b c\na b c\nx", "Ünï çödé tëxt"]
    return docs_of(spark, texts + ["one"], [None, "a", "a", None, "b", "b", "a", "", "c", None], [0, 1, 2, 3, None, 5, 6, 7, 8, 3])


def split(text):
    return (text or "").encode().lower().split() if (text or "").isascii() else (text or "").encode().translate(bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))).split()


# ---- kernel ------------------------------------------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="ab \n\té\x1f\x85 Ä", max_size=30)), max_size=8))
def test_words_match_python(texts):
    column = pa.array(texts, pa.string())
    got = []
    for a, b, h, firsts in kernel.hashed_words(column, lower=True):
        got += [h[firsts[i] : firsts[i + 1]].tolist() for i in range(b - a)]
    want = [split(t) for t in texts]
    assert [len(x) for x in got] == [len(x) for x in want]
    names: dict = {}
    for g, w in zip(got, want, strict=True):
        for x, y in zip(g, w, strict=True):
            assert names.setdefault(y, x) == x
    assert len(set(names.values())) == len(names)


def test_shingles_stay_inside_documents():
    column = pa.array(["a b c d", "", "x y", "a b c"])
    (_, _, h, firsts), = kernel.hashed_words(column, lower=True)
    runs, heads = kernel.shingle_runs(h, firsts, 3)
    assert np.diff(heads).tolist() == [2, 0, 1, 1]
    assert runs[0] == runs[3]


# ---- 1 mixing ------------------------------------------------------------------------------------------------------


def test_mix_meets_targets_and_limits(spark, odd):
    rng = random.Random(3)
    base = docs_of(spark, [" ".join(["w"] * rng.randrange(0, 400)) for _ in range(300)], [rng.choice("aaabcd") for _ in range(300)])
    for docs in (base, odd):
        rows = source_mix.mix_digest(docs).toPandas()
        assert len(rows) == docs.count()
        assert (rows.taken <= 2 * rows["size"]).all()
        for _, g in rows.groupby("source", dropna=False):
            assert abs(g.taken.sum() - g.target.iloc[0]) <= 1
            assert g.source_size.iloc[0] == g["size"].sum()
        total = rows["size"].sum()
        assert abs(rows.groupby("source", dropna=False).target.first().sum() - 1.5 * total) < 1e-6 * max(1, total)
        again = source_mix.mix_digest(docs).toPandas()
        key = ["doc_id", "size", "taken"]
        assert rows[key].sort_values(key).reset_index(drop=True).equals(again[key].sort_values(key).reset_index(drop=True))


def test_mix_interleaves_sources_evenly(spark):
    docs = docs_of(spark, ["w " * 256 for _ in range(400)], ["a", "b"] * 200)
    pieces, _, targets = source_mix.mix(docs, source_mix.MixPlan(weights=(1, 1)))
    slots = pieces.select("slot", "sid").distinct().orderBy("slot").toPandas()
    n = len(slots)
    head = slots[slots.slot < n // 4]
    assert abs((head.sid == 0).mean() - 0.5) < 0.05
    assert targets.count() == 2


def test_empty_tables(spark, odd):
    none = odd.where("false")
    assert source_mix.mix_digest(none).count() == 0
    assert line_dedup.dedup_lines(none).count() == 0
    assert quality_rules.judge(none).count() == 0
    assert shingle_join.near_duplicates(none).count() == 0
    assert decontaminate.leaks(none, spark.createDataFrame([], "item_id bigint, text string")).count() == 0
    labels = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    assert subword_quality.score(none, subword_quality.fit(none, labels, F.lit(True))).count() == 0
    assert nearest_toxic.score(none, nearest_toxic.fit(none, labels, F.lit(True))).count() == 0
    assert kneser_ney.score(none, kneser_ney.fit(none)).count() == 0


# ---- 2 archives ----------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("split_bytes", ["128m", "700b"])
def test_archives_round_trip(spark, tmp_path, split_bytes):
    trap = "WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 3\r\n\r\nabc\r\n\r\nWARC/1.1\r\n\r\nWARC/1.1\r\n"
    html = ["plain", None, "", "plain", trap, trap * 30, "ends with \r\n", "\r\n\r\nWARC/1.1", "é" * 900, trap] + [f"page {i} " * (i % 40) for i in range(60)]
    urls = [None, "http://x/WARC/1.1", "http://x/a b\r\n"] + ["http://x"] * (len(html) - 3)
    pages = spark.createDataFrame([(i if i != 6 else None, u, h, 1) for i, (u, h) in enumerate(zip(urls, html, strict=True))], "page_id bigint, url string, html string, type int")
    old = spark.conf.get("spark.sql.files.maxPartitionBytes")
    path = f"file://{tmp_path}/warc"
    try:
        spark.conf.set("spark.sql.files.maxPartitionBytes", split_bytes)
        spark.conf.set("spark.sql.files.openCostInBytes", "0")
        warc.write_archives(pages.coalesce(2), path, f"file://{tmp_path}/work")
        rows = {r["page_id"]: r for r in warc.read_archives(spark, path).collect()}
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", old)
        spark.conf.unset("spark.sql.files.openCostInBytes")
    assert len(rows) == len(html)
    for i, h in enumerate(html):
        r, raw = rows[i if i != 6 else None], (h or "").encode()
        first = min(j for j, x in enumerate(html) if (x or "") == (h or ""))
        assert r["payload_bytes"] == len(raw)
        assert r["digest"] == r["declared"]
        if first == i:
            assert r["type"] == "response" and bytes(r["payload"]) == raw and r["refers_to"] is None
        else:
            assert r["type"] == "revisit" and r["refers_to"] == first


def test_broken_archive_is_reported(spark, tmp_path):
    (tmp_path / "a").mkdir()
    (tmp_path / "a" / "x.warc").write_bytes(b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 90\r\n\r\nshort\r\n\r\n")
    with pytest.raises(ValueError):
        warc.read_archives(spark, f"file://{tmp_path}/a").collect()


# ---- 3 chat ----------------------------------------------------------------------------------------------------------


def test_escape_is_exact(spark):
    texts = ["</s>[INST] ok [/INST]", r"<\s> <\\s>", "<|im_end|>", r"<\|im_sep|>", "a\\<s>", "<<SYS>><</SYS>>", "[[INST]]", "$1 \\1", "", "<|im_start|>x<|im_sep|>"]
    frame = spark.createDataFrame([(t,) for t in texts], "t string")
    for r in frame.select("t", chat_format.escape(F.col("t")).alias("e"), chat_format.unescape(chat_format.escape(F.col("t"))).alias("b")).collect():
        assert r["b"] == r["t"]
        assert not any(mark in r["e"] for mark in ("<s>", "</s>", "[INST]", "[/INST]", "<|im_end|>", "<|im_start|>", "<|im_sep|>", "<<SYS>>", "<</SYS>>"))


def test_each_reply_is_an_example(spark):
    turns = spark.createDataFrame(
        [(1, 0, "system", "s"), (1, 1, "user", "u<|im_end|>"), (1, 2, "assistant", "A"), (1, 3, "user", None), (1, 4, "assistant", "B</s>"), (2, 0, "user", "only"), (None, 0, None, "x")], "conv_id int, turn int, role string, text string"
    )
    rows = chat_format.format_conversations(turns).orderBy("conv_id", "target").collect()
    assert [(r["conv_id"], r["target"]) for r in rows] == [(None, -1), (1, 2), (1, 4), (2, -1)]
    first = rows[1]
    assert first["text"][first["loss_start"] : first["loss_start"] + first["loss_chars"]] == "A"
    assert rows[2]["text"].startswith(first["text"])
    back = {r["conv_id"]: r for r in chat_format.read_back(chat_format.format_conversations(turns)).collect()}
    assert back[1]["n_turns"] == 5 and back[1]["loss_chars"] == 6 and back[2]["loss_chars"] == 0 and back[None]["n_turns"] == 1


# ---- 4, 5 classifiers ------------------------------------------------------------------------------------------------


def auc(score, truth):
    rank = np.argsort(np.argsort(score)) + 1
    good = truth.sum()
    return (rank[truth == 1].sum() - good * (good + 1) / 2) / (good * (len(truth) - good))


@pytest.mark.parametrize(("name", "label", "least"), [("op4_nearest_toxic", "toxic", 0.85), ("op5_subword_quality", "quality", 0.9)])
def test_classifiers_on_held_out_rows(spark, name, label, least):
    folder = "/root/testdata/sf0.01"
    rows = registry.QUERIES[name](spark, folder).toPandas()
    assert len(rows) == 1000 and rows.score.between(0, 1).all()
    joined = rows.merge(spark.read.parquet(f"{folder}/labels.parquet").toPandas(), on="doc_id")
    held = joined[joined.held_out]
    assert auc(held.score.to_numpy(), held[label].to_numpy()) >= least


@pytest.mark.parametrize(("block", "columns"), [(16, 10), (7, 0), (64, 512)])
def test_nearest_equals_brute_force(block, columns):
    rng = np.random.default_rng(0)
    dense = np.where(rng.random((300, 40)) < 0.2, rng.random((300, 40)), 0)
    dense[200:] = dense[:100]  # ties
    dense /= np.maximum(np.linalg.norm(dense, axis=1, keepdims=True), 1e-9)
    doc, term = np.nonzero(dense)
    index = nearest_toxic.BlockMaxIndex(300, doc, term, dense[doc, term], 40, block, columns)
    asked = dense[:60] * rng.uniform(0.5, 1.0, (60, 1))
    asked[7] = 0
    owner, terms = np.nonzero(asked)
    q, near, cos = index.nearest(owner, terms, asked[owner, terms], 60, 10)
    every = asked @ dense.T
    for i in range(60):
        want = np.sort(every[i][every[i] > 0])[::-1][:10]
        assert np.allclose(cos[q == i], want) and np.allclose(every[i][near[q == i]], cos[q == i])
        assert len(set(near[q == i])) == len(want)
    assert index.scored <= index.pairs


@pytest.mark.parametrize("relevance", [True, False])
def test_neighbours_and_scores_equal_brute_force_on_whole_texts(spark, relevance):
    folder = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    model = nearest_toxic.fit(docs, labels, F.lit(True), nearest_toxic.NeighbourPlan(relevance=relevance))
    rows = {r["doc_id"]: r for r in nearest_toxic.score(docs, model).collect()}
    fold = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
    parts = bytes(b for b in range(128) if not chr(b).isalnum() and (b > 32 or b in b" \t\n\x0b\x0c\r") and b != 127)
    bags = {r["doc_id"]: Counter((r["text"] or "").encode().translate(fold).translate(bytes.maketrans(parts, b" " * len(parts))).split(b" ")) for r in docs.collect()}
    for bag in bags.values():
        bag.pop(b"", None)
    df = Counter(w for bag in bags.values() for w in bag)
    y = dict(zip(model.ids.tolist(), model.toxic.tolist(), strict=True))
    held = [Counter(w for i, t in y.items() if t == side for w in bags[i]) for side in (0, 1)]
    known = set(held[0]) | set(held[1])

    def factor(w):
        idf = math.log((1 + len(bags)) / (1 + (df[w] if w in known else 1)))
        return idf * (math.log2(2 + held[1][w] / max(1, held[0][w])) if relevance and w in known else 1)

    def unit(bag):
        v = {w: (1 + math.log(n)) * factor(w) for w, n in bag.items()}
        norm = math.sqrt(sum(x * x for x in v.values()))
        return {w: x / norm for w, x in v.items()} if norm else {}

    vectors = {i: unit(bag) for i, bag in bags.items()}
    for i, v in vectors.items():
        cosine = {e: sum(x * vectors[e].get(w, 0) for w, x in v.items()) for e in y}
        want = sorted((c for c in cosine.values() if c > 0), reverse=True)[: model.plan.k]
        near = rows[i]["neighbours"]
        assert np.allclose(rows[i]["cosines"], want, atol=1e-6)
        assert np.allclose([cosine[e] for e in near], want, atol=1e-6)
        weight = np.array([1 / (1.05 - min(cosine[e], 1)) for e in near])
        toxic = np.array([y[e] for e in near])
        likely = np.interp((weight * toxic).sum() / weight.sum(), *model.steps) if near else model.alone
        copies = np.array([cosine[e] >= model.plan.copy for e in near], bool)
        if copies.any():
            likely = max(likely, ((weight * toxic)[copies].sum() + model.share) / (weight[copies].sum() + 1))
        assert abs(rows[i]["score"] - likely) < 1e-4
    assert sum(not r["neighbours"] for r in rows.values()) == sum(not any(w in known for w in bag) for bag in bags.values())


def test_copies_of_toxic_examples_score_high_whatever_their_words(spark):
    rng = random.Random(6)
    text = lambda words: " ".join(rng.choice(words) for _ in range(40))
    plain, own = [f"p{i}" for i in range(300)], lambda k: [f"own{k}x{i}" for i in range(60)]  # no two toxic texts share a word
    texts = [text(own(d)) if d % 10 == 0 else text(plain) for d in range(300)]
    labels = spark.createDataFrame([(d, int(d % 10 == 0)) for d in range(300)], "doc_id bigint, toxic int")
    docs = docs_of(spark, texts)
    model = nearest_toxic.fit(docs, labels, F.lit(True))
    toxic = [int(i) for i, y in zip(model.ids, model.toxic, strict=True) if y]
    assert len(toxic) > 5
    copies = [texts[i].rsplit(" ", 2)[0] + f" new{i} word{i}" for i in toxic] + [text(plain) for _ in range(20)]
    score = {r["doc_id"]: r["score"] for r in nearest_toxic.score(docs_of(spark, copies), model).collect()}
    assert min(score[i] for i in range(len(toxic))) >= 0.5
    assert max(score[i] for i in range(len(toxic), len(copies))) < 0.5
    assert nearest_toxic.drop_toxic(docs_of(spark, copies), model).count() == 20
    nameless = docs_of(spark, copies).withColumn("doc_id", F.lit(None).cast("bigint"))
    assert nearest_toxic.drop_toxic(nameless, model).count() == 20


@pytest.mark.parametrize(("name", "label", "least", "right"), [("op4_nearest_toxic", "toxic", 0.93, (0.98, 0.8)), ("op5_subword_quality", "quality", 0.97, (0.85, 0.98))])
def test_classifiers_on_many_held_out_rows(spark, name, label, least, right):
    folder = "/root/testdata/sf0.1"
    joined = registry.QUERIES[name](spark, folder).toPandas().merge(spark.read.parquet(f"{folder}/labels.parquet").toPandas(), on="doc_id")
    held = joined[joined.held_out]
    assert len(held) > 800 and auc(held.score.to_numpy(), held[label].to_numpy()) >= least
    for value, share in enumerate(right):
        assert (held.predicted[held[label] == value] == value).mean() >= share


def test_scores_equal_bags(spark, odd):
    plan = subword_quality.SubwordPlan(rows=1 << 12)
    rng = np.random.default_rng(0)
    model = rng.normal(0, 3, plan.rows).astype(np.float32), 0.2
    texts = [r["text"] or "" for r in odd.select("text").collect()]
    want = [1 / (1 + math.exp(-(float(model[0][rows] @ shares) + 0.2))) for rows, shares in subword_quality.bags_of(pa.array(texts), plan)]
    got = [r["score"] for r in subword_quality.score(odd, model, plan).collect()]
    assert np.allclose(sorted(got), sorted(want), atol=1e-6)
    (rows, shares), = subword_quality.bags_of(pa.array(["ab ab"]), plan)
    assert abs(shares.sum() - 1) < 1e-6 and len(rows) == 2 + len({x for w in (" ab ",) for n in (3, 4, 5) for x in (w[i : i + n] for i in range(len(w) - n + 1))})


def test_classifiers_take_odd_texts(spark, odd):
    labels = spark.createDataFrame([(3, 1, 0), (5, 0, 1), (7, None, None), (6, 1, 0), (3, 1, 0)], "doc_id bigint, quality int, toxic int")
    for rows in (subword_quality.score(odd, subword_quality.fit(odd, labels, F.lit(True))), nearest_toxic.score(odd, nearest_toxic.fit(odd, labels, F.lit(True)))):
        found = rows.toPandas()
        assert len(found) == odd.count() and found.score.between(0, 1).all()


# ---- 6 decontamination -------------------------------------------------------------------------------------------------


def test_leaks_are_found_wherever_they_stand(spark):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    items = [" ".join(word() for _ in range(n)) for n in (3, 5, 9, 14, 20, 37, 60, 150)]
    texts, want = [], set()
    for d in range(120):
        body = [word() for _ in range(rng.randrange(0, 300))]
        if d % 2:
            k = d // 2 % len(items)
            place = rng.randrange(len(body) + 1)
            body[place:place] = items[k].upper().split()
            want.add((d, k))
        texts.append(" ".join(body) + ".")
    found = decontaminate.leaks(docs_of(spark, texts), spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string")).collect()
    assert {(r["doc_id"], r["item_id"]) for r in found} == want
    assert all(r["similarity"] >= 0.8 for r in found)
    kept = decontaminate.drop_leaks(docs_of(spark, texts), spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string"))
    assert kept.count() == 60 and kept.columns == docs_of(spark, texts).columns


def test_edited_passages_are_found_as_by_brute_force():
    rng = random.Random(8)
    rule = decontaminate.LeakRule()
    words = lambda n: [f"w{rng.randrange(5000)}" for _ in range(n)]
    items = [words(n) for n in (3, 5, 11, 24, 49, 50, 59, 100, 200)]
    items.append(words(8) * 6)
    index = decontaminate.ItemIndex.build(pa.table({"item_id": pa.array(range(len(items))), "text": [" ".join(x) for x in items]}), rule)
    texts = []
    for d in range(400):
        passage = list(rng.choice(items))
        for _ in range(rng.randrange(0, 1 + max(1, len(passage) // 40))):
            kind, place = rng.choice("rrrid"), rng.randrange(len(passage))
            passage[place : place + (kind != "i")] = [] if kind == "d" else words(1)
        texts.append(" ".join(words(rng.randrange(0, 40)) + passage + words(rng.randrange(0, 40))))
    (_, _, hashes, firsts), = decontaminate.plain_words(pa.array(texts))
    found = index.matches(hashes, firsts)
    want = {}
    for d, text in enumerate(texts):
        have = text.split()
        for k, x in enumerate(items):
            wanted, n = decontaminate._shingles(np.array(x), rule.width), len(x)
            passages = [have[max(s, 0) : s + n] for s in range(1 - n, len(have))]
            best = max((decontaminate.weighted_similarity(decontaminate._shingles(np.array(p), rule.width), wanted) for p in passages if set(p) & set(x)), default=0.0)
            if best >= rule.similarity:
                want[d, k] = best
    assert len(want) > 250
    assert {x: round(v[0], 12) for x, v in found.items()} == {x: round(v, 12) for x, v in want.items()}


def test_hamming_search_finds_all_within_radius():
    rng = np.random.default_rng(2)
    rule = decontaminate.LeakRule()
    texts = [" ".join(f"w{x}" for x in rng.integers(0, 1000, 8)) for _ in range(200)]
    index = decontaminate.ItemIndex.build(pa.table({"item_id": pa.array(range(200)), "text": texts}), rule)
    for key, (prints, *_) in index.tables.items():
        flips = np.array([sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 6), replace=False)) for _ in prints], np.uint64)
        asked = prints ^ flips
        q, s = index.near(key, asked)
        want = {(i, j) for i, a in enumerate(asked) for j, p in enumerate(prints) if bin(int(a ^ p)).count("1") <= rule.radius}
        assert set(zip(q.tolist(), s.tolist(), strict=True)) == want


# ---- 7 language model ----------------------------------------------------------------------------------------------------


def test_model_distributions_sum_to_one(spark):
    rng = random.Random(4)
    texts = [" ".join(rng.choice("a b c d e f g h".split()) for _ in range(rng.randrange(1, 30))) for _ in range(200)] + [None, ""]
    model = kneser_ney.fit(docs_of(spark, texts))
    assert model.tokens == sum(len((t or "").split()) + 1 for t in texts) and model.words == 9
    for context in ("a b", "h", "", "zz a", "c zz"):
        total = 0.0
        for w in "a b c d e f g h".split() + [None]:
            (_, _, s, heads), = kneser_ney.token_streams(pa.array([context + (f" {w}" if w else "")]))
            p, _ = kneser_ney.token_probabilities(model, s, heads)
            total += p[-1] if w is None else p[-2]
        (_, _, s, heads), = kneser_ney.token_streams(pa.array([context + " unseen"]))
        total += kneser_ney.token_probabilities(model, s, heads)[0][-2]
        assert abs(total - 1) < 1e-9


def brute_probabilities(texts, discounts_of):
    """Plain dictionaries: probability of each next word by interpolated modified smoothing with every n-gram kept."""
    tri, bi, before_pair, before_word, words = Counter(), Counter(), {}, {}, Counter()
    for text in texts:
        s = ["<s>", "<s>", *(text or "").split(), "</s>"]
        for u, v, w in zip(s, s[1:], s[2:], strict=False):
            tri[u, v, w] += 1
            bi[v, w] += 1
            words[w] += 1
            before_pair.setdefault((v, w), set()).add(u)
            before_word.setdefault(w, set()).add(v)
    cont2, cont1 = {k: len(x) for k, x in before_pair.items()}, {k: len(x) for k, x in before_word.items()}
    d = {3: discounts_of(tri.values()), 2: discounts_of(cont2.values()), 1: discounts_of(cont1.values())}
    cut = lambda order, n: d[order][min(n, 3) - 1] if n else 0.0
    pairs = len(bi)

    def probability(u, v, w):
        p = max(cont1.get(w, 0) - cut(1, cont1.get(w, 0)), 0) / pairs + sum(cut(1, n) for n in cont1.values()) / pairs / (len(words) + 1)
        for order, table, context in ((2, cont2, (v,)), (3, tri, (u, v))):
            follow = {k[-1]: n for k, n in table.items() if k[:-1] == context}
            total = sum(follow.values())
            if total:
                p = max(follow.get(w, 0) - cut(order, follow.get(w, 0)), 0) / total + sum(cut(order, n) for n in follow.values()) / total * p
        return p

    return probability


def test_model_equals_plain_dictionaries(spark):
    rng = random.Random(9)
    texts = [" ".join(f"w{min(int(rng.expovariate(0.12)), 60)}" for _ in range(rng.randrange(1, 25))) for _ in range(150)] + ["x y z"] * 300 + [None, "lone words here"]
    model = kneser_ney.fit(docs_of(spark, texts).repartition(5))

    def discounts_of(counts):
        n = Counter(counts)
        return kneser_ney._discounts({f"c{k}": n[k] for k in (1, 2, 3, 4)}, "c")

    probability = brute_probabilities(texts, discounts_of)
    for text in texts[:40] + ["x y z", "x y w3", "unseen w1 w2 unseen", "lone words elsewhere", "", "w1 w1 w1 x y z z"]:
        (_, _, s, heads), = kneser_ney.token_streams(pa.array([text]))
        w = ["<s>", "<s>", *text.split(), "</s>"]
        want = [probability(*w[i : i + 3]) for i in range(len(w) - 2)]
        assert np.allclose(kneser_ney.token_probabilities(model, s, heads)[0], want, rtol=1e-9)


def test_stored_counts_are_found(tmp_path):
    rng = np.random.default_rng(3)
    for width, bits, n in ((56, 6, 4000), (38, 3, 4000), (38, 6, 300), (64, 2, 500)):
        table = kneser_ney.RangeTable(f"file://{tmp_path}/{width}-{bits}", "t", bits, width, {"n": "u1", "m": "<f8"})
        keys = np.unique(np.concatenate((rng.integers(0, 1 << min(width, 62), n, dtype=np.uint64), rng.integers(0, 64, 40, dtype=np.uint64))))
        counts = np.minimum(rng.zipf(1.3, len(keys)), 10**12)
        for part in np.unique(keys >> np.uint64(width - bits)):
            at = keys >> np.uint64(width - bits) == part
            table.save(int(part), keys[at], n=counts[at], m=counts[at] / 7)
        absent = np.setdiff1d(np.concatenate((keys + np.uint64(1), keys ^ np.uint64(1 << 33))) & np.uint64((1 << width) - 1), keys)
        asked = rng.permutation(np.concatenate((keys, keys, absent)))
        known = dict(zip(keys.tolist(), counts.tolist(), strict=True))
        found = table.find(asked)
        want = np.array([known.get(k, 0) for k in asked.tolist()])
        assert (found["n"] == want).all() and np.allclose(found["m"], want / 7)


def test_model_beats_word_counts_on_held_out(spark):
    rows = registry.QUERIES["op7_kneser_ney"](spark, "/root/testdata/sf0.01").toPandas()
    held = rows[rows.held_out]
    assert held.score.sum() > held.base_score.sum()


def test_base_score(spark, odd):
    model = kneser_ney.fit(odd)
    rows = kneser_ney.score(odd, model).toPandas()
    texts = [split(r["text"]) + [b"\n"] for r in odd.select("text").collect()]
    count = Counter(x for t in texts for x in t)
    n, v = sum(count.values()), len(count)
    want = sorted(sum(math.log10((count[x] + 1) / (n + v + 1)) for x in t) for t in texts)
    assert np.allclose(sorted(rows.base_score), want)


# ---- 8 near duplicates ------------------------------------------------------------------------------------------------------


def brute_components(texts, width, percent):
    sets = []
    for t in texts:
        w = split(t)
        sets.append(frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else []))
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(sets):
        for j in range(i):
            b = sets[j]
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return [find(i) for i in range(len(texts))], [len(s) for s in sets]


@pytest.mark.parametrize(("width", "percent", "frequent"), [(3, 90, 64), (5, 80, 8), (3, 90, 3)])
def test_groups_equal_brute_force(spark, width, percent, frequent):
    rng = random.Random(width + frequent)
    word = lambda: rng.choice("abcdefgh") + str(rng.randrange(400))
    texts = [None, "", "one", "one", "one two", "one  two"]
    for size, copies in ((400, 60), (90, 30), (66, 20), (40, 20), (12, 20), (1500, 6)):
        base = [word() for _ in range(size)]
        for _ in range(copies):
            edited = list(base)
            for _ in range(rng.randrange(0, max(2, size // 30))):
                edited[rng.randrange(size)] = word()
            texts.append(" ".join(edited))
    texts += [" ".join(word() for _ in range(rng.randrange(3, 200))) for _ in range(60)]
    line = " ".join(word() for _ in range(60))
    texts += [line + " " + " ".join(word() for _ in range(rng.randrange(0, 12))) for _ in range(40)]
    docs = docs_of(spark, texts).repartition(3)
    rule = shingle_join.JoinRule(width=width, percent=percent, frequent=frequent, block=20_000)
    rows = {r["doc_id"]: r for r in shingle_join.near_duplicates(docs, rule).collect()}
    roots, sizes = brute_components(texts, width, percent)
    assert [rows[i]["n_shingles"] for i in range(len(texts))] == sizes
    assert [rows[i]["component_id"] for i in range(len(texts))] == roots
    if width == 5:
        assert shingle_join.keep_first(docs, rule).count() == len(set(roots))


def test_groups_of_nameless_and_repeated_rows(spark):
    rng = random.Random(4)
    text = lambda n: " ".join(rng.choice("abcdefgh") + str(rng.randrange(400)) for _ in range(n))
    one, two, three = text(80), text(60), text(300_000)
    near = one + " end"
    rows = [(7, one), (None, one), (None, near), (3, near), (None, two), (None, two + " x"), (5, three), (5, three), (6, three + " y"), (8, None), (8, None), (None, ""), (9, text(30)), (9, text(30))]
    docs = spark.createDataFrame([(i, t, "a", 1, "c") for i, t in rows], "doc_id bigint, text string, row string, first int, class string")
    found = sorted(((r["doc_id"], r["component_id"]) for r in shingle_join.near_duplicates(docs).collect()), key=str)
    assert found == sorted([(7, 3), (None, 3), (None, 3), (3, 3), (None, None), (None, None), (5, 5), (5, 5), (6, 5), (8, 8), (8, 8), (None, None), (9, 9), (9, 9)], key=str)
    kept = shingle_join.keep_first(docs)
    assert kept.columns == docs.columns
    left = [(r["doc_id"], r["text"]) for r in kept.collect()]
    assert sorted(left, key=str) == sorted([(3, near), min((None, two), (None, two + " x"), key=lambda r: (r[1] not in [x[1] for x in left])), (5, three), (8, None), (8, None), (None, ""), *rows[-2:]], key=str)


def test_tokens_of_many_sets_become_frequent(spark):
    rng = random.Random(14)
    word = lambda: f"w{rng.randrange(10**6)}"
    shared = " ".join(word() for _ in range(5))
    texts = [shared + " " + " ".join(word() for _ in range(12)) for _ in range(120)]
    texts += [texts[5] + " a", texts[7], texts[9] + " b"]
    docs = docs_of(spark, texts).repartition(12)
    many = shingle_join.JoinRule(frequent=10**6, hot=10)
    roots, _ = brute_components(texts, 5, 80)
    assert {r["doc_id"]: r["component_id"] for r in shingle_join.near_duplicates(docs, many).collect()} == dict(enumerate(roots))
    index, _ = shingle_join._index(shingle_join._rows(docs), many, "file:///tmp/checkpoints/hot-tokens")
    assert index.where("not often").groupBy("key").agg(F.countDistinct("class").alias("n")).agg(F.max("n")).first()[0] <= 10


def test_leaks_of_odd_rows(spark, odd):
    rng = random.Random(6)
    item = " ".join(f"q{rng.randrange(10**6)}" for _ in range(12))
    long = " ".join(f"w{rng.randrange(10**6)}" for _ in range(200_000))  # beyond a chunk
    extra = docs_of(spark, [item, item, long + " " + item + " " + long, item.replace("q", "r")], ids=[None, 5, 77, 78]).unionByName(odd)
    bench = spark.createDataFrame([(1, item, "x"), (1, item, "x"), (2, None, "x"), (3, "  ", "x"), (None, item, "x")], "item_id bigint, text string, doc_id string")
    found = Counter((r["doc_id"], r["item_id"]) for r in decontaminate.leaks(extra, bench).collect())
    assert found == Counter({(d, k): 2 if k else 1 for d in (None, 5, 77) for k in (1, None)})
    kept = decontaminate.drop_leaks(extra, bench)
    assert kept.columns == extra.columns and kept.count() == odd.count() + 1


# ---- 9, 10 lines and rules ------------------------------------------------------------------------------------------------


def test_boilerplate_goes_and_copies_stay(spark):
    rng = random.Random(9)
    line = lambda n: " ".join(rng.choice("abcdefgh") + str(rng.randrange(10_000)) for _ in range(n))
    passage, notice, copied = line(60), line(4), [line(9) for _ in range(6)]
    texts = []
    for d in range(80):
        body = [line(8) for _ in range(4)]
        if d % 2:
            body.insert(rng.randrange(5), passage)
        if d % 3 == 0:
            body.insert(rng.randrange(5), f"  {notice}\t")
        texts.append("\n".join(body))
    texts += ["\n".join(copied)] * 12 + [None, "", passage]
    docs = docs_of(spark, texts, [f"s{i % 10}" for i in range(len(texts))])
    rows = {r["doc_id"]: r for r in line_dedup.dedup_lines(docs).collect()}
    assert len(rows) == len(texts)
    for d, t in enumerate(texts):
        want = None if t is None else "\n".join(x for x in t.split("\n") if x.strip() not in (passage, notice))
        assert rows[d]["text"] == want, d


def clean_by_hand(rows, rule=line_dedup.SpreadRule()):
    """rows: (doc_id, text, source); the cleaned texts by exact counts."""
    judged = [[x.strip(" \t\n\x0b\x0c\r") for x in (t or "").split("\n")] for _, t, _ in rows]
    judged = [[x for x in lines if len(x.split()) >= rule.min_words] for lines in judged]
    n, sites = Counter(x for lines in judged for x in lines), defaultdict(set)
    for lines, (_, _, source) in zip(judged, rows, strict=True):
        for x in lines:
            sites[x].add(source)
    spread = {x for x in n if len(sites[x]) >= max(rule.min_sites, math.ceil(rule.spread / len(x.split())))}
    out = []
    for lines, (_, t, _) in zip(judged, rows, strict=True):
        counts = sorted(n[x] if x in spread else 0 for x in lines)
        own = judged.count(lines) if len(lines) < rule.share else counts[len(counts) // rule.share]
        gone = {x for x in lines if x in spread and n[x] >= rule.times * own}
        out.append(None if t is None else "\n".join(x for x in t.split("\n") if x.strip(" \t\n\x0b\x0c\r") not in gone))
    return out


@pytest.mark.parametrize("rows_broadcast", [1_000_000, 0])
def test_spread_alone_decides_and_copies_keep_their_lines(spark, monkeypatch, rows_broadcast):
    rng = random.Random(19)
    line = lambda n: " ".join(rng.choice("abcdefgh") + str(rng.randrange(10_000)) for _ in range(n))
    passage, notice = [line(15) for _ in range(5)], line(4)  # inner lines of the passage always have the same neighbours
    texts, copied = [], [line(9) for _ in range(10)]
    for d in range(90):
        body = [line(8) for _ in range(6)]
        if d % 2:
            at = rng.randrange(7)
            body[at:at] = passage
        texts.append("\n".join(body))
    for d in range(40):  # near copies on all sites, most with the notice
        body = list(copied)
        if d % 4 == 0:
            body[rng.randrange(10)] = line(9)
        texts.append("\n".join(body + ([notice] if d % 8 else [])))
    texts += ["\n".join([line(6), notice, line(7)]) for _ in range(60)] + [notice, None, "", "\n", "x\n" + "\n".join(passage), "long " + line(200_000) + "\n" + passage[0] + "\n" + line(5)]
    rows = [(None if d in (3, 5) else d, t, None if d % 11 == 0 else f"s{d % 10}") for d, t in enumerate(texts)]
    rows += rows[:1] * 2 + rows[1:2]  # repeated rows
    docs = spark.createDataFrame([(i, t, s, "k", "g", 1) for i, t, s in rows], "doc_id bigint, text string, source string, _key string, _gone string, n_lines int")
    if not rows_broadcast:
        monkeypatch.setattr(line_dedup, "small", lambda df: False)
        monkeypatch.setattr(line_dedup, "bounded", lambda df: df)
    rule = line_dedup.SpreadRule(entries=rows_broadcast)
    found = line_dedup.dedup_lines(docs, rule)
    assert found.columns == ["doc_id", "text", "source", "_key", "_gone", "n_lines", "n_removed"]
    want = clean_by_hand(rows)
    key = lambda r: (r[0] is None, r[0] or 0, r[1] is None, r[1] or "")
    assert sorted(((r["doc_id"], r["text"]) for r in found.collect()), key=key) == sorted(((i, w) for (i, _, _), w in zip(rows, want, strict=True)), key=key)
    assert not any(p in (w or "") for w in want[:90] for p in passage)
    assert all(w.split("\n")[0] == copied[0] or d % 4 == 0 for d, w in enumerate(want[90:130]))
    assert not any(notice in w for w in want[90:190])


def test_statistics_equal_brute_force(spark, odd):
    rng = random.Random(2)
    texts = [" ".join(rng.choice("ab") for _ in range(rng.randrange(0, 60))) for _ in range(60)] + ["x " * 100, "a b c d e f g h " * 3, "#a $b |\nq\nq\n\nq", None]
    docs = docs_of(spark, texts).unionByName(odd.withColumn("doc_id", F.lit(1000) + F.coalesce("doc_id", F.lit(50))))
    truth = {r["doc_id"]: r["text"] or "" for r in docs.select("doc_id", "text").collect()}
    for r in quality_rules.text_statistics(docs).collect():
        text = truth[r["doc_id"]]
        words = text.encode().split()
        at = defaultdict(list)
        for i in range(len(words) - 7):
            at[tuple(words[i : i + 8])].append(i)
        covered = {i + k for v in at.values() if len(v) > 1 for i in v for k in range(8)}
        lines = [x for x in text.split("\n") if x.strip(" \t\n\x0b\x0c\r")]
        assert r["n_words"] == len(words)
        assert r["n_repeat_words"] == len(covered)
        assert r["n_dup_lines"] == len(lines) - len(set(lines))
        assert r["n_symbols"] == sum(c in "#*$%&|<>" for c in text)
        assert r["word_chars"] == sum(len(w.decode()) for w in words)
        assert r["n_lines"] == len(lines)
        assert r["n_upper"] == sum("A" <= c <= "Z" for c in text) and r["n_digits"] == sum("0" <= c <= "9" for c in text) and r["n_marks"] == sum(c in "!?" for c in text)
        assert r["n_distinct"] == len(set(words)) and r["n_adjacent"] == sum(a == b for a, b in zip(words, words[1:], strict=False))
        assert r["n_common"] == sum(w.decode().lower() in quality_rules.FUNCTION_WORDS for w in words)


def test_votes_are_weighed_by_what_they_agree_on(spark):
    rng = random.Random(8)
    rows = Counter()
    for _ in range(4000):
        good = rng.random() < 0.7
        votes = tuple(None if rng.random() < 0.2 else int((rng.random() < p) == good) for p in (0.9, 0.85, 0.8, 0.55))
        rows[votes] += 1
    frame = spark.createDataFrame([(*k, n) for k, n in rows.items()], "a int, b int, c int, d int, n bigint")
    model = quality_rules.fit_votes(frame, dict.fromkeys("abcd"), quality_rules.VotePrior(good=0.6, on_good=0.7, on_any=0.3, strength=1e-4), rounds=200)
    assert model["good"] == 0 and abs(model["shares"][0] - 0.7) < 0.05
    for i, p in enumerate((0.9, 0.85, 0.8, 0.55)):
        assert abs(model["rates"][0][i] - p) < 0.06
    # classes that begin the wrong way round end in the right order
    turned = quality_rules.fit_votes(frame, dict.fromkeys("abcd"), quality_rules.VotePrior(good=0.4, on_good=0.3, on_any=0.7, strength=1e-4), rounds=200)
    assert turned["good"] == 1 and abs(turned["shares"][1] - 0.7) < 0.05


def rule_votes(r):
    """The default rules once more, on a row of statistics."""
    n, chars, lines = (max(1, r[c]) for c in ("n_words", "word_chars", "n_lines"))
    vote = lambda bad, good: 0 if bad else 1 if good else None
    share = lambda x, of, bad, good: vote(x > bad * of, x <= good * of)
    return {
        "symbols": share(r["n_symbols"], n, 0.05, 0.01), "marks": share(r["n_marks"], n, 0.05, 0.01), "capitals": share(r["n_upper"], chars, 0.2, 0.1),
        "adjacent": share(r["n_adjacent"], n, 0.05, 0.01), "variety": vote(r["n_distinct"] < 0.5 * min(n, 300), r["n_distinct"] >= 0.6 * min(n, 300)),
        "repetition": share(r["n_repeat_words"], n, 0.1, 0.02), "duplicate_lines": share(r["n_dup_lines"], lines, 0.3, 0.05),
        "length": vote(r["n_words"] < 20, r["n_words"] >= 50), "function_words": vote(r["n_common"] < 0.08 * n, r["n_common"] >= 0.15 * n),
        "word_length": vote(chars > 11 * n or chars < 3 * n, 3.5 * n <= chars <= 8 * n), "digits": share(r["n_digits"], chars, 0.1, 0.02),
    }


def test_verdicts_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = [r.asDict() for r in quality_rules.judge(docs).collect()]
    names = list(quality_rules.default_rules())
    for r in rows:
        assert {n: r[f"vote_{n}"] for n in names} == rule_votes(r)
        assert r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"])
    votes = np.array([[-1 if r[f"vote_{n}"] is None else r[f"vote_{n}"] for n in names] for r in rows])
    prior = quality_rules.VotePrior()
    defects = [r.defect for r in quality_rules.default_rules().values()]
    kinds = sorted({d for d in defects if d})
    t0 = np.array([[0.97] * len(names)] + [[0.4 if d == k else 0.9 if d else 0.7 for d in defects] for k in kinds])
    p0 = np.array([0.85] + [0.15 / len(kinds)] * len(kinds))
    p, t, held = p0, t0, prior.strength * len(rows)
    for _ in range(60):
        likely = np.stack([a * np.where(votes == 1, b, np.where(votes == 0, 1 - b, 1)).prod(1) for a, b in zip(p, t, strict=True)], 1)
        q = likely / likely.sum(1, keepdims=True)
        up, cast = q.T @ (votes == 1), q.T @ (votes >= 0)
        p, before = (q.sum(0) + held * p0) / (len(rows) + held), t
        t = (up + held * p0[:, None] * t0) / (cast + held * p0[:, None])
        if np.abs(t - before).max() < 1e-6:
            break
    likely = np.stack([a * np.where(votes == 1, b, np.where(votes == 0, 1 - b, 1)).prod(1) for a, b in zip(p, t, strict=True)], 1)
    want = (likely / likely.sum(1, keepdims=True))[:, 0]
    assert np.allclose([r["posterior"] for r in rows], want, atol=1e-5)
    assert [r["kept"] for r in rows] == [not r["base_failed"] and bool(w >= 0.5) for r, w in zip(rows, want, strict=True)]


def test_verdicts_agree_with_labels(spark):
    folder = "/root/testdata/sf0.1"
    rows = registry.QUERIES["op10_quality_rules"](spark, folder).toPandas().merge(spark.read.parquet(f"{folder}/labels.parquet").toPandas(), on="doc_id")
    rows = rows[~rows.base_failed]
    assert auc(rows.posterior.to_numpy(), rows.quality.to_numpy()) > 0.98
    assert rows.kept[rows.quality == 1].mean() > 0.99 and rows.kept[rows.quality == 0].mean() < 0.05


def test_rules_take_odd_texts(spark, odd):
    rows = quality_rules.judge(odd).toPandas()
    assert len(rows) == odd.count() and rows.posterior.between(0, 1).all() and not rows.kept[rows.n_words < 20].any()


# ---- whole queries -----------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_queries_equal_sql(spark, duck, equal_rows, sf_dir, name):
    equal_rows(registry.QUERIES[name](spark, sf_dir).toPandas(), duck.sql(registry.ORACLE_SQL[name]).df())
