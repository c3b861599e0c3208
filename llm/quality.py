"""Document quality by supervised subword embeddings.

A document is the mean of learned vectors of its hashed words and character n-grams; a softmax
layer reads the mean. Vectors and layer are trained together by stochastic gradient descent in
numpy. Case is kept, for shouting and decoration tell much about quality.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from llm.store import holdout
from llm.textkit import U64, PrefixHash, join_texts, mix64, text_batches, word_spans

BITS = 17
DIM = 16
NGRAMS = (3, 4)
#: Labelled documents that training reads at most, whole, chosen by a hash of their id.
MAX_TRAIN_DOCS = 6000
THRESHOLD = 0.3


def features(texts) -> tuple[np.ndarray, np.ndarray]:
    """Bucket numbers of all features of each text, text after text, and where each text's begin (one entry more).

    Features are the words, the pairs of adjacent words and the character n-grams of words: runs of
    n characters that lie in a word, which may take in the space before it or behind it. A pair is
    hashed by the exclusive or of its words' hashes, so a word said twice is one feature, whatever the word.
    """
    buf, offsets = join_texts(texts)
    starts, ends = word_spans(buf)
    mask = (1 << BITS) - 1
    named = mix64(PrefixHash(buf).raw(starts, ends) + (ends - starts).astype(U64))
    words = (named & U64(mask)).astype(np.int32)
    pairs = (mix64(named[1:] ^ named[:-1]) & U64(mask)).astype(np.int32) + np.int32(2 << BITS)
    kept = [t if isinstance(t, str) else "" for t in texts]
    begin = np.zeros(len(kept) + 1, dtype=np.int64)
    np.cumsum([len(t) + 1 for t in kept], out=begin[1:])
    x = np.frombuffer("\n".join([*kept, ""]).encode("utf-32-le", "surrogatepass"), dtype="<u4")
    space = (x == 32) | ((x >= 9) & (x <= 13))
    grams, bounds = [], []
    for n in NGRAMS:
        size = max(0, len(x) - n + 1)
        h, split = np.zeros(size, dtype=np.uint32), np.zeros(size, dtype=bool)
        for j in range(n):
            h = h * np.uint32(0x01000193) ^ x[j : j + size]
            if 0 < j < n - 1:
                split |= space[j : j + size]
        h ^= np.uint32(n * 0x9E3779B1 & 0xFFFFFFFF)
        h *= np.uint32(0x85EBCA6B)
        at = np.flatnonzero(~split)
        grams.append((h[at] >> np.uint32(32 - BITS)).astype(np.int32) + np.int32(1 << BITS))
        bounds.append((np.searchsorted(at, begin[:-1]), np.searchsorted(at, np.maximum(begin[:-1], begin[1:] - n + 1))))
    cut = np.searchsorted(starts, offsets)
    parts, sizes = [], np.zeros(len(offsets), dtype=np.int64)
    for i in range(len(offsets) - 1):
        mine = [words[cut[i] : cut[i + 1]], pairs[cut[i] : cut[i + 1] - 1], *(g[lo[i] : hi[i]] for g, (lo, hi) in zip(grams, bounds, strict=True))] if cut[i + 1] > cut[i] else []
        parts += mine
        sizes[i + 1] = sum(map(len, mine))
    return np.concatenate(parts) if parts else np.zeros(0, np.int32), np.cumsum(sizes)


@dataclass
class SubwordModel:
    """weight: for each bucket its vector's part of the logit of label 1; bias: the logit of an empty text."""

    weight: np.ndarray
    bias: float

    def score(self, texts) -> np.ndarray:
        out = np.empty(len(texts))
        for part in text_batches(texts):
            f, at = features(texts[part])
            n = np.diff(at)
            sums = np.concatenate(([0.0], np.cumsum(self.weight[f], dtype=np.float64)))
            z = (sums[at[1:]] - sums[at[:-1]]) / np.maximum(n, 1) + self.bias
            out[part] = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        return out


def train(texts: list[str], labels: list[int], *, epochs: int = 6, lr: float = 0.5, seed: int = 3) -> SubwordModel:
    """Stochastic gradient descent, one document a step, falling rate; rare labels count more, by half the imbalance.

    Only one label among the rows, or none: a constant model.
    """
    y = np.array([int(v) for v in labels])
    if len(set(y.tolist())) < 2:
        share = float(y.mean()) if len(y) else 0.5
        return SubwordModel(np.zeros(3 << BITS, np.float32), float(np.log((share + 0.01) / (1.01 - share))))
    rng = np.random.default_rng(seed)
    vec = rng.uniform(-1 / DIM, 1 / DIM, (3 << BITS, DIM)).astype(np.float32)
    out, out_bias = np.zeros((DIM, 2), np.float32), np.zeros(2, np.float32)
    docs = []
    for part in text_batches(texts):
        f, at = features(texts[part])
        docs += [np.unique(f[a:b], return_counts=True) for a, b in zip(at[:-1], at[1:], strict=True)]
    weight = np.sqrt(len(y) / (2 * np.maximum(1, np.bincount(y, minlength=2))))
    done, total = 0, epochs * len(docs)
    for _ in range(epochs):
        for i in rng.permutation(len(docs)):
            rate = lr * (1 - done / total)
            done += 1
            f, c = docs[i]
            if not len(f):
                h = np.zeros(DIM, np.float32)
            else:
                share = (c / c.sum()).astype(np.float32)
                h = share @ vec[f]
            z = h @ out + out_bias
            d = np.exp(z - z.max())
            d /= d.sum()
            d[y[i]] -= 1
            d *= weight[y[i]]
            back = out @ d
            out -= rate * np.outer(h, d)
            out_bias -= 0.1 * rate * d
            if len(f):
                # the mean spreads a document's step over thousands of vectors; this brings it back to their scale
                vec[f] -= (rate * 20) * share[:, None] * back
    return SubwordModel((vec @ (out[:, 1] - out[:, 0])).astype(np.float32), float(out_bias[1] - out_bias[0]))


def fit(docs: DataFrame, labels: DataFrame, label_col: str, *, condition: str | None = None, max_docs: int = MAX_TRAIN_DOCS) -> SubwordModel:
    """Learn from at most max_docs labelled documents that meet the SQL condition on doc_id, each whole.

    The sample is taken from the labels first, so that only its own texts are joined and sent. Of
    rows that share an id the smallest text and the larger label count.
    """
    known = labels.select("doc_id", F.col(label_col).cast("int").alias("y")).where("y in (0, 1) and doc_id is not null")
    if condition:
        known = known.where(condition)
    known = known.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_docs)
    rows = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(known), "doc_id")  # max_docs rows bound the broadcast
    sample = rows.groupBy("doc_id", "y").agg(F.min("text").alias("text")).toPandas().sort_values(["doc_id", "text"])  # a row for each labelled document of the sample
    return train(sample["text"].tolist(), sample["y"].tolist())


def score(docs: DataFrame, model, *, text_col: str = "text", out_col: str = "score") -> DataFrame:
    """Every row with the probability of label 1 for its whole text; null counts as empty. An old column of that name is replaced."""

    @F.pandas_udf("double")
    def judge(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            yield pd.Series(model.score(texts.tolist()))

    return docs.withColumn(out_col, judge(F.col(text_col)))


HELD_OUT = holdout("doc_id", 5, 0)


def op3(spark, sf_dir: str) -> DataFrame:
    from llm.store import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels"), "quality", condition=f"not ({HELD_OUT})")
    return score(docs, model).select("doc_id", F.expr(HELD_OUT).alias("held_out"), "score", F.expr(f"cast(score >= {THRESHOLD} as int)").alias("predicted"))
