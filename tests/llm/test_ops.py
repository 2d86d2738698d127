"""The text operators against brute force, on small tables and on the edge cases that each docstring defines."""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from utilmine.llm import chat, decontamination, language_id, mixing, near_dedup, pii, quality_classifier, quality_rules, queries, sharding, substring_dedup, tokens
from utilmine.llm.components import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def frame(spark, rows):
    return spark.createDataFrame([(d, t, lang, s, len(t) if t is not None else None) for d, t, lang, s in rows], SCHEMA)


def made_words(rng, n):
    return [rng.choice("alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi".split()) + str(rng.randrange(40)) for _ in range(n)]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and blank texts, a long repetitive text, ties, repeated rows, and columns with names that operators use."""
    rng = random.Random(3)
    base = " ".join(made_words(rng, 120))
    rows = [(1, base, "en", "a"), (1, base, "en", "a"), (2, base, None, None), (None, base, "en", "a"), (None, None, None, None), (3, None, "de", "b"), (4, "", "en", "b"), (5, " \t\n", "en", "b"), (6, "x " * 30_000, "en", "a"), (7, base + " tail", "fr", None), (8, "🙂 é ß", "fr", "c"), (9, "one two", "en", "c")]
    clash = [F.lit("x").alias(c) for c in ("size", "key", "bucket", "node", "label", "shard", "slot", "target", "copies", "kept", "quality", "band")]
    return frame(spark, rows).select("*", *clash)


def test_words_and_hashes():
    texts = ["a b  c", "", None, "c d a", "x"]
    block = next(tokens.blocks(pa.array(texts)))
    block.words()
    assert block.counts.tolist() == [len(WORD.findall(t or "")) for t in texts]
    h = block.hashes()
    assert h[0] == h[4] and h[2] != h[1] and len(set(h.tolist())) == 5
    small = list(tokens.blocks(pa.array(texts), 3))
    assert [len(b) for b in small] and sum(len(b) for b in small) == len(texts)
    two = next(tokens.blocks(pa.array(["p q r s t", "q r s t"])))
    two.words()
    found, owner = two.shingles(two.hashes(), 3)
    assert found[1:3].tolist() == found[3:].tolist() and owner.tolist() == [0, 0, 0, 1, 1]


def brute_passages(docs, width=50):
    """docs: (doc_id, text); the contract's result by sets of windows."""
    first = {}
    for d, t in docs:
        w = (t or "").encode().split()
        for i in range(len(w) - width + 1):
            k = tuple(w[i : i + width])
            first[k] = min(first.get(k, 1 << 62), d if d is not None else 1 << 61)
    out = []
    for d, t in docs:
        w = (t or "").encode().split()
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            if first[tuple(w[i : i + width])] < (d if d is not None else 1 << 61):
                gone[i : i + width] = [True] * width
        out.append((d, len(w), sum(gone), hashlib.sha256(b" ".join(x for x, g in zip(w, gone, strict=True) if not g)).hexdigest()))
    return Counter(out)


def test_op1_random(spark):
    rng = random.Random(1)
    passages = [made_words(rng, n) for n in (49, 50, 51, 80, 200)] + [["same"] * 70, ["a", "b"] * 60, ["r", "r", "s"] * 40]
    docs = []
    for d in range(60):
        parts = [rng.choice(passages) if rng.random() < 0.5 else made_words(rng, rng.randrange(0, 70)) for _ in range(rng.randrange(1, 5))]
        docs.append((d, " ".join(x for p in parts for x in (p if rng.random() < 0.7 else p[rng.randrange(3) :]))))
    rng.shuffle(docs)
    got = substring_dedup.dedup_passages(spark.createDataFrame(docs, "doc_id long, text string"))
    assert Counter(map(tuple, got.collect())) == brute_passages(docs)


def test_op1_edges(spark, odd):
    docs = [(r["doc_id"], r["text"]) for r in odd.collect()]
    assert Counter(map(tuple, substring_dedup.dedup_passages(odd).collect())) == brute_passages(docs)
    assert substring_dedup.dedup_passages(odd.where("false")).count() == 0
    kept = substring_dedup.dedup_passages(odd, with_text=True).where("doc_id = 7").first()
    assert kept["kept_text"].split()[-1] == "tail" and kept["n_removed"] == 120
    with pytest.raises(ValueError):
        substring_dedup.Passages(20)


def check_shards(rows, docs, n):
    assert Counter((r["doc_id"], r["text"]) for r in rows) == Counter((d[0], d[1]) for d in docs)
    slots = defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in slots.values()) and set(slots) <= set(range(n))


def test_op2(spark, odd):
    docs = [(r["doc_id"], r["text"]) for r in odd.collect()]
    for size in (8 << 20, 2000):
        rows = sharding.shards(odd.select("doc_id", "text"), 5, bucket_bytes=size).collect()
        check_shards(rows, docs, 5)
    again = sharding.shards(odd.repartition(3).select("doc_id", "text"), 5, bucket_bytes=2000).collect()
    assert Counter(map(tuple, rows)) == Counter(map(tuple, again))
    assert sharding.shards(odd.where("false"), 5).count() == 0
    ids = spark.range(5000).select(F.col("id").alias("doc_id"))
    moved = ids.select(sharding.shard_of(F.col("doc_id"), 40, 7).alias("a"), sharding.shard_of(F.col("doc_id"), 41, 7).alias("b")).collect()
    assert all(a == b or b == 40 for a, b in moved) and 60 < sum(b == 40 for _, b in moved) < 190


def test_op2_query(spark, sf):
    rows = {r["doc_id"]: r for r in queries.op2_sharding(spark, sf).collect()}
    for r in spark.read.parquet(f"{sf}/documents.parquet").collect():
        own = rows[r["doc_id"]]
        assert (own["size"], own["text_crc32"]) == (len(r["text"].encode()) + 16, zlib.crc32(r["text"].encode()))


def test_op3_round_trip(spark, sf):
    hard = ["</s>[INST] ok [/INST]", "<|turn|>", "<\\|end|>x<|end|>\n", "<\\\\|text|>", "", "a\nb", "<|turn|>user<|text|>", "\\<|end|>", "<<SYS>><</SYS>>"]
    for s in hard:
        assert chat.unescape(chat.escape(s)) == s
        assert not any(c in chat.escape(s) for c in chat.CONTROLS)
    rows = [(1, i, ("user", "assistant", "sys<|text|>tem")[i % 3], s) for i, s in enumerate(hard)] + [(2, 0, "assistant", None), (None, None, None, None), (3, 1, "user", "b"), (3, 1, "user", "b"), (3, 0, "assistant", "a")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r["conv_id"]: r for r in chat.read_back(chat.format_conversations(df)).collect()}
    assert [(t["role"], t["text"]) for t in got[1]["turns"]] == [(r[2], r[3]) for r in rows[: len(hard)]]
    assert got[1]["loss"] == "".join(r[3] for r in rows[: len(hard)] if r[2] == "assistant")
    assert [t["text"] for t in got[3]["turns"]] == ["a", "b", "b"] and got[2]["loss"] == "" and len(got[None]["turns"]) == 1
    assert chat.format_conversations(df.where("false")).count() == 0


def test_op4(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    clean = " ".join(["the anea is of enre and tion"] * 3) + " in this eras."
    more = frame(spark, [(10_000 + i, " ".join(random.Random(i).sample(clean.split(), 20)), "en", "src0") for i in range(20)] + [(20_000, "### $$$ %%% ||| *** &&& " * 20, "en", "src0"), (20_001, None, None, None), (None, "a", None, "src0")])
    got = {r["doc_id"]: r for r in quality_classifier.classify(docs.unionByName(more.select(docs.columns)), labels).collect()}
    truth = [(r["doc_id"], r["quality"] == 1 and r["toxic"] == 0) for r in labels.collect() if r["doc_id"] in got]
    assert sum(got[d]["kept"] == good for d, good in truth) >= 0.85 * len(truth)
    assert all(got[10_000 + i]["kept"] for i in range(20)) and not got[20_000]["kept"] and not got[20_001]["kept"]
    assert quality_classifier.classify(docs.where("false"), labels).count() == 0
    none = quality_classifier.classify(docs, labels.where("false")).collect()
    assert all(r["kept"] and r["quality"] == 0.5 for r in none)


def test_op4_shrinks_sparse_sites(spark):
    rows = [("big", "p", 0.9)] * 400 + [("small", "p", 0.9)] + [("other", "p", 0.1)] * 400 + [("other", "q", 0.9)]
    got = {(r["__host"], r["__path"]): r for r in quality_classifier.site_rates(spark.createDataFrame(rows, "__host string, __path string, __bad double")).collect()}
    assert got["big", "p"]["path_rate"] > 0.85
    assert got["small", "p"]["rate"] < got["small", "p"]["path_rate"] < 0.9
    assert got["other", "q"]["path_rate"] < 0.9


def test_op5_base(spark, odd):
    texts = ["a@b.c x@y.zz.q-1 a@b @c.d", "1.2.3.4 256.1.1.1 1.2.3.4.5.6.7.8 0001.2.3.4", "4111 1111 1111 1111 41111111111111112 4111-1111-1111-1111", "+1 (743) 555-3824 +12 +123456789012345678", "é +49 30 1234567é a.b@c.de", None, ""]
    got = [pii.base_spans(t or "") for t in texts]
    assert [(k, (t or "")[a:b]) for t, s in zip(texts, got, strict=True) for k, a, b in s] == [
        ("email", "a@b.c"), ("email", "x@y.zz.q-1"), ("ip", "1.2.3.4"), ("ip", "1.2.3.4"), ("ip", "5.6.7.8"), ("ip", "0001.2.3.4"),
        ("phone", "+1 (743) 555-3824"), ("email", "a.b@c.de"), ("phone", "+49 30 1234567"),
    ]
    assert pii.base_spans("x 4111-1111-1111-1111.") == [("card", 2, 21)]
    assert pii.find(odd).count() == odd.count() and pii.find(odd.where("false")).count() == 0
    assert pii.redact("mail a@b.co now", "email:5:11") == "mail [EMAIL] now"


def test_op5_added_spans_and_held_out():
    trained = pii.models()
    for text, want in [("call (743) 555-3824 now", True), ("write bob.smith at host dot com please", True), ("built 2024-10-12 10:22 on", False), ("at 12.5, 13.7 and 14.8 degrees", False), ("is at and. Ereast. For", False), ("the sum of 12 and 30 is 42", False)]:
        assert bool(pii.all_spans([text], trained)[0][1]) == want, text
    for number, kind in enumerate(pii.KINDS):
        rng, right = np.random.default_rng([99, number]), []
        for _ in range(400):
            s, good = pii._made(kind, rng)
            p = trained[kind][0].probability(np.asarray([pii.features(kind, f"zz {s} zz", 3, 3 + len(s))], float))[0]
            right.append((p >= 0.5) == bool(good))
        assert np.mean(right) > 0.9


def test_op6_brute_force(spark):
    rng = random.Random(5)
    items = [(i, " ".join(made_words(rng, n))) for i, n in enumerate((12, 12, 30, 30, 60, 4, 1))] + [(7, None), (8, "")]
    docs = []
    for d in range(40):
        w = made_words(rng, 80)
        if d % 2 == 0:
            own = items[rng.randrange(6)][1].split()
            if d % 4 == 0 and len(own) > 20:
                own[rng.randrange(len(own))] = "changed"
            at = rng.randrange(80)
            w[at:at] = [x.upper() if d % 3 == 0 else x for x in own]
        docs.append((d, "; ".join(w) if d % 5 == 0 else " ".join(w)))
    docs += [(None, items[2][1]), (100, None), (101, "")]
    got = {(r["doc_id"], r["item_id"]): r["similarity"] for r in decontamination.contaminated(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    plain = lambda t: re.findall(r"[0-9a-z]+", (t or "").lower())
    shingles = lambda w, k: Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1))
    want = {}
    for d, t in docs:
        w = plain(t)
        for i, it in items:
            x = plain(it)
            k = min(5, len(x))
            for p in range(len(w) - len(x) + 1) if x else ():
                a, b = shingles(w[p : p + len(x)], k), shingles(x, k)
                s = sum((a & b).values()) / sum((a | b).values())
                if s >= 0.8:
                    want[d, i] = max(want.get((d, i), 0), s)
    assert got == pytest.approx(want) and len(want) > 15
    empty = spark.createDataFrame([], "item_id long, text string")
    assert decontamination.contaminated(spark.createDataFrame(docs, "doc_id long, text string"), empty).count() == 0
    with pytest.raises(ValueError):
        decontamination.benchmark_index(spark.createDataFrame(items, "item_id long, text string"), 10)


def test_op6_shorter_documents(spark):
    """Items cut at either end: a document shorter than the item is compared whole."""
    rng = random.Random(6)
    items = [(i, " ".join(made_words(rng, n))) for i, n in enumerate((50, 16, 59, 6, 5))]
    docs = [(50, " ".join(items[0][1].split()[:46]))]
    for i, t in items:
        w = t.split()
        for cut in (1, 2, 4, 9, 20):
            docs += [(100 * i + 2 * cut, " ".join(w[cut:])), (100 * i + 2 * cut + 1, " ".join(w[: max(0, len(w) - cut)]))]
    docs += [(1000, items[0][1]), (1001, items[0][1] + " more words")]
    want = {}
    for d, t in docs:
        w = t.split()
        for i, it in items:
            x = it.split()
            n = min(len(x), len(w))
            for p in range(len(w) - n + 1):
                a, b = (Counter(tuple(v[j : j + 5]) for j in range(len(v) - 4)) for v in (w[p : p + n], x))
                s = sum((a & b).values()) / max(1, sum((a | b).values()))
                if s >= 0.8:
                    want[d, i] = max(want.get((d, i), (0, 0)), (s, n))
    docs_, items_ = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): (r["similarity"], r["n_words"]) for r in decontamination.contaminated(docs_, items_).collect()}
    assert got == want and got[50, 0] == (pytest.approx(42 / 46), 46)
    assert {r["doc_id"] for r in decontamination.without_contaminated(docs_, items_).collect()} == {d for d, _ in docs} - {d for d, _ in want}


def test_op6_index_finds_all_within_radius():
    rng = np.random.default_rng(0)
    index = decontamination.Index([(i, " ".join(f"w{rng.integers(1000)}" for _ in range(20))) for i in range(30)])
    prints = index.prints[rng.integers(30, size=300)]
    for _ in range(decontamination.RADIUS):
        prints = prints ^ (np.uint64(1) << rng.integers(64, size=300).astype(np.uint64))
    w, i = index.candidates(prints, 20)
    near = np.argwhere(np.bitwise_count(prints[:, None] ^ index.prints[None, :]) <= decontamination.RADIUS)
    assert set(zip(w.tolist(), i.tolist(), strict=True)) == set(map(tuple, near.tolist()))


def rule_counts(t):
    w = WORD.findall(t or "")
    seen, dup = set(), 0
    for line in (t or "").split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    c, covered = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4)), set()
    for i in range(len(w) - 4):
        if c[tuple(w[i : i + 5])] > 1:
            covered.update(range(i, i + 5))
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t or ""), dup, len(covered), len(w) < 10 or 100 * len(covered) > 20 * len(w)


def test_op7(spark, odd, sf):
    docs = odd.select("doc_id", "text").unionByName(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text"))
    got = Counter((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) for r in quality_rules.score(docs).collect())
    assert got == Counter((r["doc_id"], *rule_counts(r["text"])) for r in docs.collect())
    assert "Python" not in quality_rules.score(odd)._jdf.queryExecution().executedPlan().toString()
    assert quality_rules.score(odd.where("false")).count() == 0


def test_op8(spark, sf, odd):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    truth = {r["doc_id"]: r["lang"] for r in docs.collect()}
    got = language_id.identify(docs).collect()
    held = [r for r in got if r["held_out"]]
    assert {r["doc_id"] for r in held} == {d for d in truth if zlib.crc32(str(d).encode()) % 3 == 1}
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in held]) > 0.95 and all(0 <= r["score"] <= 1 for r in got)
    rows = {(r["doc_id"], r["lang_pred"]) for r in language_id.identify(odd).collect()}
    assert {(3, "und"), (4, "und"), (5, "und")} <= rows and not any(d in (6, 9) and p == "und" for d, p in rows)
    assert language_id.identify(odd.where("false")).count() == 0
    swapped = language_id.identify(docs.withColumn("lang", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, "xx").otherwise(F.col("lang")))).collect()
    assert sorted(map(tuple, swapped)) == sorted(map(tuple, got))


def filled(sizes):
    """Targets by repeated resharing; sizes by source, in order."""
    weight = {s: i % 3 + 1 for i, s in enumerate(sizes)}
    left, open_, target = float(sum(sizes.values())), set(sizes), {}
    while open_:
        whole = sum(weight[s] for s in open_)
        over = {s for s in open_ if left * weight[s] / whole > 3 * sizes[s]}
        if not over:
            target |= {s: left * weight[s] / whole for s in open_}
            break
        target |= {s: 3.0 * sizes[s] for s in over}
        left -= sum(target[s] for s in over)
        open_ -= over
    return target


@pytest.mark.parametrize("seed", range(2))
def test_op9(spark, seed):
    rng = random.Random(seed)
    rows = [(i, " ".join(made_words(rng, rng.randrange(0, 60))), "en", rng.choice(["a", "b", "c", "é", None] + ["hot"] * 10 * seed)) for i in range(800)] + [(900, "only " * 4, "en", "tiny"), (901, None, "en", "void")]
    docs = frame(spark, rows)
    got = mixing.mix(docs).collect()
    sizes = defaultdict(int)
    for _, t, _, s in rows:
        sizes[s] += len(WORD.findall(t or ""))
    ordered = {s: sizes[s] for s in [*sorted(x for x in sizes if x is not None), None] if s in sizes}
    want, taken = filled(ordered), defaultdict(int)
    source = {r[0]: r[3] for r in rows}
    for r in got:
        s = source[r["doc_id"]]
        assert r["target"] == pytest.approx(want[s]) and r["source_size"] == ordered[s] and r["copies"] <= 3
        taken[s] += r["size"] * r["copies"]
    assert all(abs(taken[s] - want[s]) <= 60 for s in want)
    assert Counter(map(tuple, mixing.mix(docs.repartition(7)).collect())) == Counter(map(tuple, got))
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == docs.columns and mixed.count() == sum(r["copies"] for r in got)
    assert "Python" not in mixed._jdf.queryExecution().executedPlan().toString()


def test_op9_edges(odd):
    assert mixing.mix(odd).count() == odd.count() and mixing.mixed_documents(odd).columns == odd.columns
    assert mixing.mix(odd.where("false")).count() == 0


def near_classes(docs):
    shingles = {d: {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for d, t in docs for w in [(t or "").encode().split()]}
    label = {d: d for d in shingles}
    for a in shingles:
        for b in shingles:
            if a < b and len(shingles[a] & shingles[b]) >= 0.8 * len(shingles[a] | shingles[b]):
                x, y = sorted((label[a], label[b]))
                label = {k: x if v == y else v for k, v in label.items()}
    return label


def test_op10_brute_force(spark):
    rng = random.Random(9)
    docs, d = [], 0
    for _ in range(12):
        base = made_words(rng, rng.randrange(3, 200))
        for _ in range(rng.choice([1, 1, 2, 45])):
            w = list(base)
            for _ in range(rng.randrange(0, 6)):
                w[rng.randrange(len(w))] = f"edit{rng.randrange(10**6)}"
            docs.append((d, " ".join(w)))
            d += 1
    got = {r["doc_id"]: r["class_id"] for r in near_dedup.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    want = near_classes(docs)
    # links by weighted similarity alone may join plain classes; none of these is parted
    assert len({(want[d], got[d]) for d in want}) == len(set(want.values()))
    assert len(set(got.values())) >= 0.9 * len(set(want.values()))


def test_op10_repeated_passages(spark):
    """A passage and the same pasted many times: near by plain similarity, far by weighted."""
    rng, docs = random.Random(11), []
    for i in range(60):
        base = " ".join(made_words(rng, 60))
        docs += [(2 * i, base), (2 * i + 1, " ".join([base] * (20 if i % 2 else 2)))]
    want = near_classes(docs)
    assert len(set(want.values())) == 60
    got = {r["doc_id"]: r["class_id"] for r in near_dedup.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == want


def test_op10_unlike_asks_both_measures(spark):
    n = near_dedup.ROWS * near_dedup.BANDS
    rows = [(1, 2, 1, 2, [0] * n + list(range(n)), [1] * n + list(range(n))), (3, 4, 3, 4, list(range(n)) + [0] * n, list(range(n)) + [1] * n), (5, 6, 5, 6, [0] * 2 * n, [1] * 2 * n), (7, 8, 7, 7, [0] * 2 * n, [0] * 2 * n)]
    pairs = spark.createDataFrame(rows, "node long, b long, label long, label_b long, samples array<int>, samples_b array<int>")
    assert sorted(map(tuple, near_dedup.NearCopies._unlike(pairs).collect())) == [(1, 2), (3, 4)]


def test_op10_edges(odd):
    rows = near_dedup.near_duplicates(odd).collect()
    by = Counter((r["doc_id"], r["class_id"], r["class_size"]) for r in rows)
    assert by[1, 1, 5] == 2 and by[2, 1, 5] == 1 and by[7, 1, 5] == 1 and by[4, 3, 4] == 1
    kept = near_dedup.without_near_copies(odd)
    assert kept.columns == odd.columns and sorted(r["doc_id"] for r in kept.collect()) == [1, 3, 6, 8, 9]
    assert near_dedup.near_duplicates(odd.where("false")).count() == 0


def test_op10_blocks_span_links():
    rng = random.Random(2)
    base = made_words(rng, 100)
    texts = []
    for i in range(60):
        w = list(base)
        for _ in range(i % 7):
            w[rng.randrange(100)] = f"edit{rng.randrange(10**6)}"
        texts.append(" ".join(w))
    label = near_dedup.block_links(pa.array(texts), np.ones(1 << near_dedup.FREQUENCY_BITS, np.float32), 0.8)
    want = near_classes(list(enumerate(texts)))
    assert label.tolist() == [want[i] for i in range(60)]


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 102), (102, 101), (5, 5)]
    got = {r["node"]: r["label"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100, 102: 100}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
