"""The pipeline, stage by stage, against brute force; the queries with SQL against DuckDB; and what `fit` makes of odd labels."""

import os
import re
from collections import defaultdict

import duckdb
import numpy as np
import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F

import corpus_pipeline
from semimul.llm import bpe, quality_classifier, toxicity
from semimul.llm import queries as llm
from tests.llm.test_operators import brute_near, frame, words

DATA = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Tables with toxic documents, shared lines, exact and near copies, benchmark passages, and odd rows."""
    rng, texts, labels = np.random.default_rng(8), {}, []
    line = "All rights to this very page are reserved by its author."
    passage = words(rng, 40)
    for i in range(240):
        w = words(rng, 60, 700)
        if i % 6 == 0:
            for p in rng.integers(0, 60, 4):
                w[p] = str(rng.choice(["nastyone", "nastytwo", "vileword"]))
        if i % 17 == 1:
            w[20:20] = passage[5:30]
        texts[i] = " ".join(w) + ("\n " + (line.upper() if i % 2 else line) if i % 9 == 2 else "")
        labels.append((i, 1, int(i % 6 == 0)))
    for i in range(240, 270):
        source = texts[(i - 240) * 5 + 1].split(" ")
        if i % 2:
            source[10] = "changed"
        texts[i] = " ".join(source)
    texts |= {270: None, 271: "", 272: "  \n ", 273: "one", 274: "a b " * 4000}
    path = str(tmp_path_factory.mktemp("tables"))
    docs = frame(spark, texts.items())
    docs.write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels + labels[:3] + [(None, 1, 1), (9999, None, None)], "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    spark.createDataFrame([(1, " ".join(passage)), (2, None), (3, "")], "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    return path


def rows(df):
    return {r.doc_id: r.text for r in df.collect()}


def by_lines(texts):
    key = lambda x: "".join(c.lower() if c.isascii() else c for c in x.strip(" \t\n\x0b\x0c\r"))
    held = defaultdict(set)
    for i, t in texts.items():
        for x in (t or "").split("\n"):
            if len(key(x)) >= 40:
                held[key(x)].add(i)
    return {i: "\n".join(x for x in (t or "").split("\n") if len(held.get(key(x), ())) < 5 or i == max(held[key(x)])) for i, t in texts.items()}


def by_benchmark(texts, items):
    cut = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if c.isascii() else c for c in t or ""))
    windows = {tuple(w[k : k + 13]) for w in map(cut, items) for k in range(max(1, len(w) - 12) if w else 0)}
    kept = {}
    for i, t in texts.items():
        w, hit = cut(t), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    hit.update(range(k, k + n))
        if not hit or 20 * len(hit) < len(w):
            kept[i] = t
    return kept


def test_stages_equal_brute_force(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    labels = spark.read.parquet(f"{folder}/labels.parquet")
    texts, stages = rows(docs), dict(corpus_pipeline.STAGES)
    assert list(stages) == ["toxicity", "line dedup", "near dedup", "decontamination", "byte-level BPE"]

    model = toxicity.fit(docs, labels)
    want = {i: t for i, t in texts.items() if model.score((t or "").encode()) < 0.7}
    kept = stages["toxicity"](spark, docs, folder)
    vile = {i for i, t in texts.items() if any(x in (t or "") for x in ("nastyone", "nastytwo", "vileword"))}
    assert rows(kept) == want and kept.columns == docs.columns
    assert len(vile - set(want)) >= 0.9 * len(vile) and len(set(texts) - set(want) - vile) <= 0.02 * len(texts)

    docs = spark.createDataFrame(kept.collect(), docs.schema)
    want = by_lines(rows(docs))
    kept = stages["line dedup"](spark, docs, folder)
    assert rows(kept) == want and kept.columns == docs.columns and want != rows(docs)
    assert {r.doc_id: r.n_chars for r in kept.collect()} == {i: len(t) for i, t in want.items()}

    docs = spark.createDataFrame(kept.collect(), docs.schema)
    texts = rows(docs)
    want = {i: texts[i] for i, (_, c) in brute_near(texts, 5).items() if i == c}
    kept = stages["near dedup"](spark, docs, folder)
    assert rows(kept) == want and kept.columns == docs.columns and len(want) < len(texts) - 15

    docs = spark.createDataFrame(kept.collect(), docs.schema)
    texts = rows(docs)
    want = by_benchmark(texts, [r.text for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect()])
    kept = stages["decontamination"](spark, docs, folder)
    assert rows(kept) == want and kept.columns == docs.columns and len(want) < len(texts) - 5

    with open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        known = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(f.read()), special_tokens={})
    got = {r.doc_id: np.frombuffer(bytes(r.ids), "<u4").tolist() for r in stages["byte-level BPE"](spark, spark.createDataFrame(kept.collect(), docs.schema), folder).collect()}
    assert got == {i: known.encode_ordinary(t or "") for i, t in want.items()}

    whole = {r.doc_id: np.frombuffer(bytes(r.ids), "<u4").tolist() for r in corpus_pipeline.run(spark, folder).collect()}
    assert whole == got


@pytest.mark.parametrize("name, stage", corpus_pipeline.STAGES)
def test_stages_take_odd_tables(spark, folder, name, stage):
    none = frame(spark, [])
    assert stage(spark, none, folder).count() == 0
    odd = frame(spark, [(1, None), (2, ""), (2, ""), (3, "one two"), (None, "no id " * 30), (None, None), (5, "x" * 100_000)])
    odd = odd.withColumn("lang", F.lit(None).cast("string")).withColumn("source", F.lit(None).cast("string")).withColumn("n_chars", F.lit(None).cast("long"))
    kept = stage(spark, odd, folder).collect()
    assert len(kept) == 7 and sorted(str(r.doc_id) for r in kept) == ["1", "2", "2", "3", "5", "None", "None"]


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
@pytest.mark.parametrize("name", sorted(llm.ORACLES))
def test_query_equals_its_sql(spark, name):
    duck = duckdb.connect()
    for table in ("documents", "benchmark"):
        duck.execute(f"CREATE VIEW {table} AS SELECT * FROM '{DATA}/{table}.parquet'")
    got = llm.QUERIES[name](spark, DATA)
    cur = duck.execute(llm.ORACLES[name])
    columns = [c[0] for c in cur.description]
    assert sorted(columns) == sorted(got.columns)
    assert sorted(map(str, (tuple(r[c] for c in columns) for r in got.collect()))) == sorted(map(str, cur.fetchall()))


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_op2_and_op9_equal_brute_force_on_the_given_tables(spark):
    texts = rows(spark.read.parquet(f"{DATA}/documents.parquet"))
    want = {i: (n, c, i == c) for i, (n, c) in brute_near(texts, 4).items()}
    assert {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in llm.op2_near_dedup(spark, DATA).collect()} == want


@pytest.mark.parametrize("labels", [[], [(1, 1, 1)], [(1, 0, 0)], [(1, 1, 1), (1, 0, 0), (1, 1, 1), (2, None, None), (None, 1, 1), (3, 7, 7), (99, 0, 0)]])
def test_fit_takes_odd_labels(spark, labels):
    """Empty, one-sided, repeated, contradicting, null and unknown labels; null and very long texts. Every score is a probability."""
    docs = frame(spark, [(1, "good words here"), (2, None), (3, "x y " * 30_000), (4, ""), (1, "good words here")])
    table = spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    for module, name in ((quality_classifier, "quality"), (toxicity, "toxic")):
        for frame_ in (docs, frame(spark, [])):
            got = [r.score for r in module.score(docs, module.fit(frame_, table), name="score").collect()]
            assert len(got) == 5 and all(0 <= s <= 1 for s in got), name
            assert got == [r.score for r in module.score(docs, module.fit(frame_, table), name="score").collect()]


def test_long_texts_are_sampled_all_over(spark):
    text = "".join(chr(97 + k // 4000) for k in range(80_000))
    got = bytes(frame(spark, [(1, text)]).select(toxicity.sampled(F.col("text"), 16_000).alias("t")).first().t)
    assert len(got) == 16_000 and got[:2000] == b"a" * 2000 and got[-2000:] == b"t" * 2000 and len(set(got)) >= 8
    assert bytes(frame(spark, [(1, "short")]).select(toxicity.sampled(F.col("text"), 16_000).alias("t")).first().t) == b"short"


def test_the_risk_step_equals_a_plain_rendering():
    """The non-negative estimate of the risk on clean text, by its definition over small matrices."""
    rng = np.random.default_rng(0)
    toxic = [(" ".join(words(rng, 20, 50)) + " vileword nastyone").encode() for _ in range(60)]
    mixed = [" ".join(words(rng, 20, 50)).encode() for _ in range(400)] + toxic[:40]
    model = toxicity.train(toxic, mixed, 0.1)
    z = lambda t: np.log(model.score(t) / (1 - model.score(t)))
    soft = lambda x: np.logaddexp(0, x)
    zp, zu = np.array(list(map(z, toxic))), np.array(list(map(z, mixed)))
    prior = 0.1
    clean = soft(zu).mean() - prior * soft(zp).mean()
    risk = prior * soft(-zp).mean() + max(0.0, clean)
    start = np.log(prior / (1 - prior))
    assert risk < prior * soft(-start) + (1 - prior) * soft(start) and (zp > 0).all() and np.mean(zu[:400] < 0) == 1


def test_score_equals_the_sum_of_its_features():
    model = toxicity.Model({i: 0.5 for w in (b"vile", b"nasty") for i in toxicity.features(w)}, -2.0)
    found = set().union(*(toxicity.features(w) for w in (b"vile", b"nasty")))
    assert abs(model.score(b"Vile, vile NASTY plain") - 1 / (1 + np.exp(2.0 - 0.5 * len(found)))) < 1e-12
    good, bad = [b"plain good words " * 20] * 9, [b"#### bad $$$$ " * 20] * 9
    quality = quality_classifier.train(good, bad, 0.8)
    x = np.dot(quality.weights, quality.features(good[0]))
    assert abs(quality.score(good[0]) - 1 / (1 + np.exp(-x))) < 1e-12 and quality.score(good[0]) > 0.5 > quality.score(bad[0])


def test_toxicity_trains_in_a_task(spark, monkeypatch):
    """The sample and its features never stand in the driver's memory, and the model is that of the plain call."""
    docs = frame(spark, [(n, "vile nasty words" if n % 4 == 0 else f"plain text {n % 7}") for n in range(400)])
    labels = spark.createDataFrame([(n, int(n % 4 == 0)) for n in range(400)], "doc_id long, toxic int")
    rows = docs.filter(~toxicity.held_out(F.col("doc_id"))).collect()
    prior = labels.filter(~toxicity.held_out(F.col("doc_id"))).agg(F.avg("toxic")).first()[0]
    want = toxicity.train([r.text.encode() for r in rows if r.doc_id % 4 == 0], [r.text.encode() for r in rows], prior)

    def never(*_, **__):
        raise AssertionError("trained on the driver")

    monkeypatch.setattr(toxicity, "train", never)
    got = toxicity.fit(docs, labels)
    assert got.weights.keys() == want.weights.keys() and got.weights
    assert all(abs(got.weights[i] - want.weights[i]) < 1e-6 for i in want.weights) and abs(got.bias - want.bias) < 1e-6
