"""Language identification by a string kernel: blended-spectrum n-gram presence, Nystrom landmarks, one-versus-rest kernel ridge regression.

The kernel of two texts is the mean over n = 1..4 of the cosine of their n-gram presence vectors (bytes of the case-folded text, hashed
into fixed tables). Landmarks are a stratified part of a bounded sample of learnable documents. With K the kernel matrix of the
landmarks, features K(x, L) K**-1/2 feed a ridge regression with targets 1 and -1 for each language.

Scoring: for a block of texts, presence matrices times landmark matrices give K(x, L), times the weights the decision values.
As the kernel is linear in the normalised presence vectors, the two products are folded into one matrix for each n before scoring.

Defined results: `und` with score 0 for a null text or one without a letter; repeated rows get equal results; an empty table gives an empty result; with no learnable
document every prediction is `und`. A null doc_id is neither held out nor learned from.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from utilmine.llm import tokens
from utilmine.llm.tokens import Block, mix

SPECTRUM = (1, 2, 3, 4)
TABLE_BITS = {1: 8, 2: 12, 3: 13, 4: 13}
#: Bounds on the documents that a fit reads and on landmarks, by language.
SAMPLE, LANDMARKS = 300, 60
RIDGE, SHARPNESS = 1e-2, 4.0
UNKNOWN = "und"
#: Bytes and texts of a block, whose matrices take about 84 kB a text; bytes of a text that a fit reads.
BLOCK, BLOCK_TEXTS = 1 << 18, 256
MOST_BYTES = 1 << 20

_FOLD = np.arange(256, dtype=np.uint64)
_FOLD[65:91] += 32
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123)]] = True


def presence(block: Block) -> list[np.ndarray]:
    """For each n a matrix of texts by table entries, rows of norm 1 (or 0 for texts shorter than n)."""
    data = _FOLD[block.data]
    owner = np.repeat(np.arange(len(block)), np.diff(block.bounds))
    out, grams = [], np.zeros(len(data), np.uint64)
    for n in SPECTRUM:
        size = max(len(data) - n + 1, 0)
        grams = (grams[:size] << np.uint64(8)) | data[n - 1 : n - 1 + size]
        inside = owner[:size] == owner[n - 1 : n - 1 + size]
        bits = TABLE_BITS[n]
        slot = grams if n == 1 else mix(grams + np.uint64(n)) >> np.uint64(64 - bits)
        m = np.zeros((len(block), 1 << bits), np.float32)
        m[owner[:size][inside], slot[inside].astype(np.int64)] = 1
        norms = np.sqrt(m.sum(1, keepdims=True))
        out.append(m / np.maximum(norms, 1))
    return out


class Model:
    """Folded weights: for each n a matrix of table entries by languages."""

    def __init__(self, languages: list[str], folded: list[np.ndarray], bias: np.ndarray):
        self.languages, self.folded, self.bias = languages, folded, bias

    def decide(self, block: Block) -> np.ndarray:
        return sum(m @ w for m, w in zip(presence(block), self.folded, strict=True)) + self.bias


def fit(texts: list[str], langs: list[str], landmarks: int = LANDMARKS, ridge: float = RIDGE) -> Model | None:
    languages = sorted(set(langs))
    if not languages:
        return None
    parts = [presence(b) for b in tokens.blocks(pa.array(texts, pa.large_string()), BLOCK, BLOCK_TEXTS)]
    x = [np.concatenate(p) for p in zip(*parts, strict=True)]
    lang = np.array([languages.index(v) for v in langs])
    chosen = np.concatenate([np.flatnonzero(lang == i)[:landmarks] for i in range(len(languages))])
    scale = 1 / len(SPECTRUM)
    k_xl = scale * sum(m.astype(float) @ m[chosen].T.astype(float) for m in x)
    values, vectors = np.linalg.eigh(k_xl[chosen])
    root = vectors / np.sqrt(np.maximum(values, 1e-8 * values.max()))  # features: K(x, L) root
    features = np.hstack([k_xl @ root, np.ones((len(lang), 1))])
    targets = np.where(lang[:, None] == np.arange(len(languages)), 1.0, -1.0)
    share = np.bincount(lang, minlength=len(languages))
    weight = (1 / share[lang])[:, None]
    penalty = ridge * np.eye(features.shape[1]) / len(languages)
    penalty[-1, -1] = 1e-9
    beta = np.linalg.solve(features.T @ (weight * features) + penalty, features.T @ (weight * targets))
    alpha = root @ beta[:-1]
    return Model(languages, [(scale * m[chosen].T @ alpha).astype(np.float32) for m in x], beta[-1])


def learnable_sample(docs: DataFrame, most: int, most_bytes: int = MOST_BYTES) -> tuple[list[str], list[str]]:
    """About `most` different texts of each language (at most twice as many), the least by a hash of language and text among those that may be learned from.

    Texts over most_bytes are not learned from (they are scored like all). Equal texts of a language are one, so no number of copies or repeated ids
    reaches the driver; what does is bounded by 2 * most * most_bytes a language.
    """
    may = docs.where("doc_id is not null and lang is not null and text is not null and not held_out").where(F.octet_length("text") <= most_bytes)
    may = may.select("lang", "text", F.xxhash64(F.lit(5), "lang", "text").alias("draw"))
    counts = {r["lang"]: r["n"] for r in may.groupBy("lang").agg(F.approx_count_distinct("draw").alias("n")).collect()}
    few = F.lit(False)
    for lang, n in counts.items():
        few = few | ((F.col("lang") == lang) & (F.shiftrightunsigned("draw", 34) < int(min(1.0, 1.5 * most / n) * (1 << 30)) + 1))
    drawn = may.where(few).groupBy("lang", "draw").agg(F.min("text").alias("text"))
    place = F.row_number().over(Window.partitionBy("lang").orderBy("draw"))  # over about 1.5 * most rows of a language
    rows = drawn.withColumn("place", place).where(F.col("place") <= 2 * most).select("lang", "draw", "text").collect() if counts else []
    rows = sorted(rows, key=lambda r: (r["draw"], r["lang"]))
    return [r["text"] for r in rows], [r["lang"] for r in rows]


def _has_letter(block: Block) -> np.ndarray:
    sums = np.append(0, np.cumsum(_LETTER[block.data], dtype=np.int64))
    found = sums[block.bounds[1:]] > sums[block.bounds[:-1]]
    for i in np.flatnonzero(~found):
        found[i] = any(c.isalpha() for c in block.text(i).decode("utf-8", "replace"))
    return found


def _predictor(model: Model | None):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names, scores = [], []
            for block in tokens.blocks(batch.column(2), BLOCK, BLOCK_TEXTS):
                found = _has_letter(block) & (model is not None)
                values = model.decide(block) if model else np.zeros((len(block), 1))
                e = np.exp(SHARPNESS * (values - values.max(1, keepdims=True)))
                best = values.argmax(1)
                names += [model.languages[b] if f else UNKNOWN for b, f in zip(best, found, strict=True)]
                scores.append(np.where(found, 1 / e.sum(1), 0.0))
            yield pa.record_batch({"doc_id": batch.column(0), "held_out": batch.column(1), "lang_pred": pa.array(names, pa.string()), "score": pa.array(np.concatenate(scores) if scores else np.zeros(0))})

    return rows


def identify(docs: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, lang_pred, score for each row of docs (doc_id, text, lang); lang is read from learnable rows alone."""
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))
    rows = docs.select("doc_id", held.alias("held_out"), "text", "lang")
    texts, langs = learnable_sample(rows, sample)
    kind = docs.schema["doc_id"].dataType.simpleString()
    return rows.select("doc_id", "held_out", "text").mapInArrow(_predictor(fit(texts, langs)), f"doc_id {kind}, held_out boolean, lang_pred string, score double")
