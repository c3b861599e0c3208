"""Language identification by a byte-level convolutional network.

Bytes are folded to 32 symbols (letters without case, the low bits of continuation bytes, five
kinds of lead bytes, one boundary symbol). Filters of widths 2 and 3 slide over fixed-length windows, each is max-pooled
over its window, and a softmax layer reads the pooled values. It is trained in numpy with Adam.

Scoring evaluates the same network without visiting a position twice: a filter's response
depends only on the n-gram under it, so the responses of all 32**width n-grams are computed
once, and the maximum over a window is the maximum over the distinct n-grams it holds.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from llm.store import fresh, holdout
from llm.textkit import tidy

UNDETERMINED = "und"
WINDOW = 1024
#: Documents that training reads at most, whole, chosen by a hash of their id.
MAX_TRAIN_DOCS = 6000

SYMBOLS = 32
_letter = regex.compile(r"\p{L}")


def _symbol_table() -> np.ndarray:
    sym = np.zeros(256, dtype=np.int32)
    for lower, upper in zip(range(97, 123), range(65, 91), strict=True):
        sym[lower] = sym[upper] = lower - 96
    sym[0x80:0xC0] = np.arange(0x80, 0xC0) & 31  # accents: upper and lower case differ by 32
    for k, lead in enumerate((0xC0, 0xC4, 0xD0, 0xE0, 0xF0)):  # Latin-1, further two-byte letters, other alphabets, three bytes, four bytes
        sym[lead:] = 27 + k
    return sym


SYMBOL = _symbol_table()


@dataclass
class ByteConvNet:
    """langs: output labels in order; filters[w]: (w, SYMBOLS, n) weights; bias, out, out_bias: the dense layers."""

    langs: list[str]
    filters: dict[int, np.ndarray]
    bias: np.ndarray
    out: np.ndarray
    out_bias: np.ndarray

    def tables(self) -> dict[int, np.ndarray]:
        """Response of every filter of width w to each of the SYMBOLS**w n-grams."""
        made = {}
        for w, f in self.filters.items():
            t = f[0]
            for j in range(1, w):
                t = (t[:, None, :] + f[j][None, :, :]).reshape(-1, f.shape[2])
            made[w] = np.ascontiguousarray(t, dtype=np.float32)
        return made


def codes(symbols: np.ndarray, width: int) -> np.ndarray:
    """n-gram numbers along the last axis."""
    n = symbols.shape[-1] - width + 1
    out = symbols[..., :n]
    for j in range(1, width):
        out = (out << 5) | symbols[..., j : j + n]
    return out


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def train(texts: list[str], labels: list[str], *, seed: int = 7, steps: int = 700, width_filters: dict[int, int] | None = None, lr: float = 0.01) -> ByteConvNet:
    """Fit the network to texts with known languages.

    Each step takes windows of one length, cycling from 16 to WINDOW bytes, cut at random
    places, so that short and long texts are both learned. One label only: a net that always
    answers it. No texts: a net without languages, for which every text is undetermined.
    """
    if not texts:
        return ByteConvNet([], {2: np.zeros((2, SYMBOLS, 1), np.float32)}, np.zeros(1, np.float32), np.zeros((1, 0), np.float32), np.zeros(0, np.float32))
    rng = np.random.default_rng(seed)
    langs = sorted(set(labels))
    y_all = np.array([langs.index(x) for x in labels])
    data = [SYMBOL[np.frombuffer(t.encode("utf-8", "surrogatepass"), dtype=np.uint8)] for t in texts]
    by_lang = [np.flatnonzero(y_all == k) for k in range(len(langs))]
    widths = width_filters or {2: 24, 3: 40}
    total = sum(widths.values())
    p: dict = {w: rng.normal(0, 0.3, (w, SYMBOLS, n)).astype(np.float32) for w, n in widths.items()}
    p["b"], p["o"], p["ob"] = np.zeros(total, np.float32), rng.normal(0, 0.2, (total, len(langs))).astype(np.float32), np.zeros(len(langs), np.float32)
    m, v = ({k: np.zeros_like(x) for k, x in p.items()} for _ in range(2))
    lengths = (16, 32, 64, 256, WINDOW)
    for step in range(1, steps + 1):
        size = lengths[step % len(lengths)]
        batch = int(np.clip(16384 // size, 16, 256))
        pick = np.array([rng.choice(by_lang[k]) for k in rng.integers(0, len(langs), batch)])  # languages in equal shares
        x = np.zeros((batch, size), dtype=np.int32)
        for i, d in enumerate(pick):
            s = data[d]
            at = rng.integers(0, max(1, len(s) - size + 1))
            cut = s[at : at + size]
            x[i, : len(cut)] = cut
        pooled, spots = [], []
        for w in widths:
            n = size - w + 1
            r = sum(p[w][j][x[:, j : j + n]] for j in range(w))
            spot = r.argmax(axis=1)
            spots.append(spot)
            pooled.append(np.take_along_axis(r, spot[:, None, :], axis=1)[:, 0])
        z = np.concatenate(pooled, axis=1) + p["b"]
        h = np.maximum(z, 0)
        prob = _softmax(h @ p["o"] + p["ob"])
        d_out = prob
        d_out[np.arange(batch), y_all[pick]] -= 1
        d_out /= batch
        g = {"o": h.T @ d_out, "ob": d_out.sum(0)}
        dz = (d_out @ p["o"].T) * (z > 0)
        g["b"] = dz.sum(0)
        at = 0
        for (w, n_f), spot in zip(widths.items(), spots, strict=True):
            grad = np.zeros_like(p[w])
            part = dz[:, at : at + n_f]
            at += n_f
            cols = np.broadcast_to(np.arange(n_f), spot.shape)
            for j in range(w):
                np.add.at(grad[j], (np.take_along_axis(x, spot + j, axis=1), cols), part)
            g[w] = grad
        rate = lr * min(1, 4 * (1 - step / (steps + 1)))
        for k, grad in g.items():
            m[k] = 0.9 * m[k] + 0.1 * grad
            v[k] = 0.99 * v[k] + 0.01 * grad * grad
            p[k] = p[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-6)
    return ByteConvNet(langs, {w: p[w] for w in widths}, p["b"], p["o"], p["ob"])


def predict(net: ByteConvNet, texts, tables: dict[int, np.ndarray] | None = None, rows: int = 256) -> tuple[list[str], np.ndarray]:
    """Language and probability of each whole text.

    A text is cut into windows of WINDOW bytes, the last one padded; its probabilities are the
    mean over its windows, weighted by their letters. Null, empty or letterless: 'und' with 0.
    """
    if not net.langs:
        return [UNDETERMINED] * len(texts), np.zeros(len(texts))
    tables = tables or net.tables()
    raw = [t.encode("utf-8", "surrogatepass") if isinstance(t, str) and _letter.search(t) else b"" for t in texts]
    counts = np.array([-(-len(r) // WINDOW) for r in raw], dtype=np.int64)
    owner = np.repeat(np.arange(len(raw)), counts)
    flat = np.frombuffer(b"".join(r.ljust(c * WINDOW, b"\0") for r, c in zip(raw, counts.tolist(), strict=True)), dtype=np.uint8).reshape(-1, WINDOW)
    sums = np.zeros((len(raw), len(net.langs)))
    for a in range(0, len(flat), rows):
        x = SYMBOL[flat[a : a + rows]]
        pooled = []
        for w, t in tables.items():
            n_codes = SYMBOLS**w
            seen = np.zeros(len(x) * n_codes, dtype=bool)
            seen[(codes(x, w) + (np.arange(len(x)) * n_codes)[:, None]).ravel()] = True
            hit = np.flatnonzero(seen)
            first = np.searchsorted(hit, np.arange(len(x)) * n_codes)
            pooled.append(np.maximum.reduceat(t[hit % n_codes], first, axis=0))
        h = np.maximum(np.concatenate(pooled, axis=1) + net.bias, 0)
        weight = (x > 0).sum(axis=1, keepdims=True) + 1e-3
        np.add.at(sums, owner[a : a + rows], _softmax((h @ net.out + net.out_bias).astype(np.float64)) * weight)
    best = sums.argmax(axis=1)
    totals = sums.sum(axis=1)
    score = np.where(totals > 0, sums[np.arange(len(raw)), best] / np.where(totals > 0, totals, 1), 0.0)
    return [net.langs[k] if n else UNDETERMINED for k, n in zip(best.tolist(), counts.tolist(), strict=True)], np.clip(score, 0, 1)


def fit(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", condition: str | None = None, max_docs: int = MAX_TRAIN_DOCS) -> ByteConvNet:
    """Learn from at most max_docs labelled documents that meet the SQL condition, each whole; their number does not grow with the table. Of rows that share an id the one with the smallest text counts."""
    known = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"), F.col(lang_col).alias("y")).where("t is not null and y is not null and t rlike '\\\\p{L}'")
    if condition:
        known = known.where(condition.replace(id_col, "i"))
    rank = F.xxhash64("i")
    last = known.select(rank.alias("h")).orderBy("h").limit(max_docs).agg(F.max("h")).first()[0]  # hashes alone: texts of rows beyond the sample are never sent
    if last is None:
        return train([], [])
    one = known.where(rank <= last).groupBy("i").agg(F.min(F.struct("t", "y")).alias("x"))
    sample = one.orderBy(rank, "i").limit(max_docs).select("i", "x.t", "x.y").toPandas().sort_values(["i", "t"])
    return train(sample["t"].tolist(), sample["y"].astype(str).tolist())


def identify(docs: DataFrame, net: ByteConvNet, *, text_col: str = "text") -> DataFrame:
    """Every row of docs with lang_pred and lang_score (existing columns of those names are replaced); whole texts, one narrow pass.

    The text is handed to Python beside the row, so other columns, whatever their names, pass
    through untouched. Null, empty and letterless texts: 'und' with score 0; an empty table stays
    empty; repeated rows are judged alike.
    """
    tables = net.tables()
    rest = docs.drop("lang_pred", "lang_score")

    @F.pandas_udf("lang string, score double")
    @tidy
    def judge(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for texts in batches:
            lang, score = predict(net, texts.tolist(), tables)
            yield pd.DataFrame({"lang": lang, "score": score})

    lid = fresh(rest, "__lid")
    out = rest.withColumn(lid, judge(F.col(text_col)))
    return out.select(*[F.col(f"`{c}`") for c in rest.columns], F.col(f"{lid}.lang").alias("lang_pred"), F.col(f"{lid}.score").alias("lang_score"))


def filter_stage(docs: DataFrame, net: ByteConvNet, min_score: float = 0.3) -> DataFrame:
    """Documents in a recognised language, all their columns; 'und' and texts of which no language reaches min_score go. A net that has learned no language rejects nothing."""
    if not net.langs:
        return docs
    own = docs
    for name in ("lang_pred", "lang_score"):  # columns of these names are the documents' own here
        if name in docs.columns:
            own = own.withColumnRenamed(name, fresh(docs, f"__{name}"))
    judged = identify(own, net).where((F.col("lang_pred") != UNDETERMINED) & (F.col("lang_score") >= min_score))
    return judged.select(*[F.col(f"`{o}`").alias(c) for o, c in zip(own.columns, docs.columns, strict=True)])


HELD_OUT = holdout("doc_id", 3, 1)


def op7(spark, sf_dir: str) -> DataFrame:
    from llm.store import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    net = fit(docs, condition=f"not ({HELD_OUT})")
    return identify(docs.select("doc_id", "text"), net).select("doc_id", F.expr(HELD_OUT).alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))
