"""Clashing names, null and repeated ids, repeated rows and very long texts, through operators and pipeline stages with all columns."""

from __future__ import annotations

import random
import time
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from utilmine.llm import decontamination, language_id, mixing, near_dedup, pii, quality_classifier, sharding, tokens
from utilmine.llm.shared import unused_prefix

NAMES = ("shard", "slot", "shard_", "bucket", "key", "other", "node", "label", "mark", "size", "copies", "stays", "_in0", "__key", "__host", "__shard", "__size", "a.b")


@pytest.fixture(scope="module")
def clashing(spark):
    base = " ".join(f"word{i} and" for i in range(60))
    rows = [(1, base, "en", "a"), (1, base, "en", "a"), (2, base, None, None), (None, base, "en", "a"), (None, None, None, None), (3, None, "de", "b"), (4, "", "en", "b"), (7, base + " tail", "fr", None), (8, "one two", "en", "c")]
    docs = spark.createDataFrame([(*r, len(r[1] or "")) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    return docs.select("*", *(F.concat(F.lit(f"{c}:"), F.coalesce("doc_id", F.lit(0))).alias(c) for c in NAMES))


def told(df, columns):
    return Counter(tuple(r) for r in df.select(*(F.col(f"`{c}`") for c in columns)).collect())


def test_stages_keep_clashing_columns(spark, clashing, sf):
    columns, all_rows = clashing.columns, told(clashing, clashing.columns)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        for docs in (clashing, clashing.where("false")):
            kept = stage(spark, docs, sf)
            assert kept.columns == columns, name
            found = told(kept, columns)
            assert set(found) <= set(all_rows), name
            if docs is clashing and name == "benchmark decontamination":
                assert found == all_rows
    assert told(near_dedup.without_near_copies(clashing), ["doc_id"])[(1,)] == 1
    kept = quality_classifier.without_rejected(clashing, spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    assert told(kept, columns) == all_rows


def test_op2_clashing_columns(spark, clashing):
    out = sharding.shards(clashing, 5)
    assert out.columns[-2:] == ["shard", "slot"] and len(set(out.columns)) == len(out.columns) == len(clashing.columns) + 2
    assert told(out, ["doc_id", "text", "shard__", "slot_", "__shard"]) == told(clashing, ["doc_id", "text", "shard", "slot", "__shard"])
    assert unused_prefix(clashing) == "___"


def test_op5_base_is_the_patterns():
    rng = random.Random(4)
    for _ in range(5000):
        t = "".join(rng.choice("ab.@-1 25+(é0.@.") for _ in range(rng.randrange(60)))
        assert pii.base_spans(t) == [(k, m.start(), m.end()) for k in pii.KINDS for m in pii.BASE[k].finditer(t) if pii.holds(k, m.group())]
    assert pii.base_spans("1.1.1." + "0" * 6000) == [("ip", 0, 6006)]


def test_op5_taken():
    rng = random.Random(5)
    for _ in range(300):
        made = lambda n: [("x", a, a + rng.randrange(1, 9)) for a in (rng.randrange(60) for _ in range(n))]
        spans = made(rng.randrange(6))
        taken = pii.Taken(spans)
        for _, a, b in made(10):
            assert taken.overlaps(a, b) == any(x < b and a < y for _, x, y in spans)
            if not taken.overlaps(a, b):
                taken.add(a, b)
                spans.append(("x", a, b))


def test_op5_very_long_texts():
    trained = pii.models()
    spent = []
    for n in (20_000, 80_000):
        texts = ["a.b@c.de " * (n // 9), "f" * n + " x@y.zz", "1" * n, "1.1" * (n // 3)]
        start = time.process_time()
        (mails, _), (one, _), *_ = pii.all_spans(texts, trained)
        spent.append(time.process_time() - start)
        assert len(mails) == n // 9 and one == [("email", n + 1, n + 7)]
    assert spent[1] < 10 * spent[0] + 1  # four times the text; quadratic is sixteen times


def test_op6_null_and_repeated_items(spark):
    text = " ".join(f"w{i}" for i in range(30))
    items = spark.createDataFrame([(None, text), (5, None), (5, text), (5, "other " * 20), (None, None), (6, "")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "x " + text), (2, "nothing here"), (None, text)], "doc_id long, text string")
    assert Counter((r["doc_id"], r["item_id"]) for r in decontamination.contaminated(docs, items).collect()) == Counter([(1, None), (1, 5), (None, None), (None, 5)])


def test_op6_covered():
    rng = np.random.default_rng(1)
    for _ in range(200):
        starts, span = rng.integers(-5, 40, rng.integers(1, 6)), int(rng.integers(1, 12))
        want = sorted({p for s in starts for p in range(s, s + span) if 2 <= p < 37})
        assert decontamination.covered(starts, span, 2, 37).tolist() == want


def test_op8_sample_is_bounded(spark):
    rows = [(7, f"le chat noir {i % 3}", "fr") for i in range(5000)] + [(i, f"the black cat {i}", "en") for i in range(2000)] + [(9, "x" * 3000, "xx")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("held_out", F.lit(False))
    got = Counter(language_id.learnable_sample(docs, 100, 2000)[1])
    assert got["fr"] == 3 and 50 < got["en"] <= 200 and "xx" not in got
    assert language_id.learnable_sample(docs, 100) == language_id.learnable_sample(docs.repartition(7), 100)
    assert max(len(b) for b in tokens.blocks(pa.array(["a b"] * 1000), 1 << 18, 256)) == 256


def test_op8_folded_weights_equal_the_kernel():
    """Decision values from folded weights against kernel values with every landmark and ridge regression written out."""
    rng = random.Random(2)
    words = {"de": "der die und nicht ein haus".split(), "en": "the and not a house of".split()}
    langs = [rng.choice(list(words)) for _ in range(40)]
    texts = [" ".join(rng.choice(words[v]) for _ in range(rng.randrange(1, 20))) for v in langs]
    model = language_id.fit(texts, langs, landmarks=10, ridge=0.1)

    def kernel(a, b):
        x, y = (language_id.presence(next(tokens.blocks(pa.array([t])))) for t in (a, b))
        return sum(float((u * v).sum()) for u, v in zip(x, y, strict=True)) / len(x)

    marks = [t for v in sorted(words) for t in [t for t, o in zip(texts, langs, strict=True) if o == v][:10]]
    k_ll = np.array([[kernel(a, b) for b in marks] for a in marks])
    k_xl = np.array([[kernel(a, b) for b in marks] for a in texts])
    values, vectors = np.linalg.eigh(k_ll)
    root = vectors / np.sqrt(np.maximum(values, 1e-8 * values.max()))
    x = np.hstack([k_xl @ root, np.ones((40, 1))])
    y = np.array([[1.0 if v == o else -1.0 for o in sorted(words)] for v in langs])
    w = np.array([1 / langs.count(v) for v in langs])[:, None]
    penalty = np.diag([0.1 / 2] * (x.shape[1] - 1) + [1e-9])
    want = x @ np.linalg.solve(x.T @ (w * x) + penalty, x.T @ (w * y))
    got = model.decide(next(tokens.blocks(pa.array(texts))))
    assert np.abs(got - want).max() < 5e-3


def test_op9_equal_rows_are_split(spark):
    row = spark.createDataFrame([(3, "one two three", "en", "b", 13)], "doc_id long, text string, lang string, source string, n_chars long")
    equal = row.withColumn("again", F.explode(F.array_repeat(F.lit(0), 1000))).drop("again")
    other = row.select(F.lit(4).cast("long").alias("doc_id"), F.lit("four five").alias("text"), "lang", F.lit("a").alias("source"), "n_chars")
    docs = equal.unionByName(other.withColumn("again", F.explode(F.array_repeat(F.lit(0), 600))).drop("again"))
    rows = mixing.mix(docs).groupBy("doc_id").agg(F.first("target").alias("target"), F.sum(F.col("size") * F.col("copies")).alias("taken"), F.count(F.lit(1)).alias("n"), F.max("copies").alias("most")).collect()
    assert {r["doc_id"]: r["n"] for r in rows} == {3: 1000, 4: 600}
    assert all(abs(r["taken"] - r["target"]) <= 3 and r["most"] <= 3 for r in rows)
    assert mixing.mixed_documents(docs).groupBy("doc_id").count().join(spark.createDataFrame([(r["doc_id"], r["taken"]) for r in rows], "doc_id long, taken long"), "doc_id").where("taken != count * if(doc_id = 3, 3, 2)").count() == 0
