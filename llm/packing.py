"""Best-fit packing of tokenised documents into sequences of bounded length.

The lengths' histogram is all the planner sees. Lengths are grouped into classes of UNIT tokens;
a configuration linear program (how often to use each multiset of classes that fits a sequence)
is solved by multiplicative weights: a configuration that is used makes its classes lighter, and
the next one is the heaviest, found by a knapsack dynamic program over the capacity. The same
weights give a dual bound. The fractional solution is rounded down and what is left, a number of
pieces that does not grow with the corpus, is placed by best fit with exact lengths.
The plan's size depends on the capacity alone, so it is safe to ship to every executor.
"""

from __future__ import annotations

import gc
import re
import struct
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from numpy.lib.stride_tricks import as_strided
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from llm.store import keep, workspace
from llm.textkit import text_batches, tidy

CAPACITY = 4096
UNIT = 4
#: Units that the knapsack prices at once.
BLOCK = 16
END_ID = 1
#: Chunks of text whose ids one Python worker remembers, twice at most; beyond that it forgets those not met lately.
CACHE_CHUNKS = 600_000


def default_tokenizer_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


# The pre-tokenisation pattern of the vocabulary file, for Latin text.
_word = re.compile(r"[^\W\d_]+|'(?:s|t|re|ve|m|ll|d)|\d|(?:[^\s\w]|_)+")
#: Characters for which the shortcut below could differ from the library, and the mark of special tokens.
_other = re.compile("[\x00-\x08\x0e-\x1f\x7f-\xa0\xad\xb2\xb3\xb9\xbc-\xbeİɐ-\U0010ffff]|<\\|")
#: Those of them that one byte can stand for.
_other_bytes = bytes(b for b in range(256) if _other.match(chr(b)))


def needs_library(text: str) -> bool:
    """Whether the text has any of these, for texts of Latin-1 without a look at every character."""
    try:
        raw = text.encode("latin-1")
    except UnicodeEncodeError:
        return _other.search(text) is not None
    return len(raw.translate(None, _other_bytes)) < len(raw) or "<|" in text




class _Known(dict):
    """Ids by chunk; a chunk that is asked for before it is known is noted in `new`, once, and answered with None. What was known before the last renewal comes back when it is asked for."""

    def __init__(self):
        super().__init__()
        self.new: list[str] = []
        self.old: dict[str, bytes] = {}

    def __missing__(self, chunk):
        ids = self[chunk] = self.old.get(chunk)
        if ids is None:
            self.new.append(chunk)
        return ids

    def renew(self):
        """Forget what has not been asked for since the last renewal."""
        self.old = dict(self)
        self.clear()


#: Words of which the library's own pattern makes one word, and that its normalisers leave as they are.
_plain = re.compile("[a-zß-öø-ÿ]+")


class WordTokenizer:
    """Ids of whole texts as little-endian uint32 bytes, equal to the library's for every text.

    The vocabulary splits text into words before it merges, and no word holds white space, so the
    ids of a chunk between white space do not depend on its neighbours and can be remembered.
    Texts beyond Latin letters, with control characters or with marks of special tokens go
    through the library whole.
    """

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.known = _Known()
        # the characters that stand for the bytes of plain words beyond ASCII
        as_bytes = ByteLevel(add_prefix_space=False, use_regex=False)
        self.spelt = {ord(c): as_bytes.pre_tokenize_str(c)[0][0] for c in map(chr, range(0xDF, 0x100)) if _plain.fullmatch(c)}
        vocab = self.library.get_vocab()
        self.ends_word = np.zeros(max(vocab.values()) + 1, dtype=bool)
        self.ends_word[[i for token, i in vocab.items() if token.endswith("</w>")]] = True

    @staticmethod
    def _pack(ids) -> bytes:
        return struct.pack(f"<{len(ids)}I", *ids)

    def encode(self, texts) -> list[bytes]:
        known = self.known
        if len(known) > CACHE_CHUNKS:
            known.renew()
        chunks = [None if needs_library(t) else t.lower().split() for t in texts]
        # one look-up for each chunk: those met for the first time are noted, and filled in afterwards
        found = [None if c is None else list(map(known.__getitem__, c)) for c in chunks]
        if known.new:
            self._learn(known.new)
            known.new = []
            found = [f if f is None or None not in f else list(map(known.__getitem__, cs)) for f, cs in zip(found, chunks, strict=True)]
        return [self._pack(self.library.encode(t, add_special_tokens=False).ids) if f is None else b"".join(f) for t, f in zip(texts, found, strict=True)]

    def _learn(self, chunks: list[str]) -> None:
        """Ids of new chunks: those of their words, one after the other. A word is a chunk of its own."""
        known, mixed, rare = self.known, {}, {}
        for c in chunks:
            if _plain.fullmatch(c):
                known[c] = self._merged(c)
            else:
                mixed[c] = _word.findall(c)
        for words in mixed.values():
            for w in words:
                if known.get(w) is None:
                    if (ids := known.old.get(w)) is not None:
                        known[w] = ids
                    elif _plain.fullmatch(w):
                        known[w] = self._merged(w)
                    else:
                        rare[w] = None
        self._look_up(list(rare))
        for c, words in mixed.items():
            known[c] = b"".join([known[w] for w in words])

    def _merged(self, word: str) -> bytes:
        """Ids of a plain word, from the model alone."""
        return self._pack([t.id for t in self.model.tokenize(word if word.isascii() else word.translate(self.spelt))])

    def _look_up(self, words: list[str], chunk: int = 500) -> None:
        """Ids of other words, many to a call: in a line of words, an id that ends a word says where to cut."""
        parts = [words[a : a + chunk] for a in range(0, len(words), chunk)]
        for part, e in zip(parts, self.library.encode_batch_fast([" ".join(p) for p in parts], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, dtype="<u4")
            cut, raw = (4 * (np.flatnonzero(self.ends_word[ids]) + 1)).tolist(), ids.tobytes()
            for word, a, b in zip(part, [0, *cut], cut, strict=False):
                self.known[word] = raw[a:b]
            if len(cut) != len(part):  # never seen; then word by word
                for word in part:
                    self.known[word] = self._pack(self.library.encode(word, add_special_tokens=False).ids)


_tokenizers: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """One for each Python worker."""
    if path not in _tokenizers:
        _tokenizers[path] = WordTokenizer(path)
    return _tokenizers[path]


PIECE_SCHEMA = "doc_id long, piece int, start long, length int, ids_crc32 long"


def pieces(docs: DataFrame, *, tokenizer_file: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row for each piece of each document: only documents of more than `capacity` ids are cut. Null text counts as empty; every document ends with end_id, so none is without a piece."""
    tail = np.array([end_id], dtype="<u4").tobytes()

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tok = tokenizer(tokenizer_file or default_tokenizer_file())
        gc.disable()  # strings and numbers make no cycles, and there are millions of them
        for df in batches:
            texts = [t if isinstance(t, str) else "" for t in df["text"]]
            n, which, start, length, crc = 0, [], [], [], []
            for part in text_batches(texts):
                for ids in tok.encode(texts[part]):
                    ids += tail
                    total = len(ids) // 4
                    for a in range(0, total, capacity):
                        which.append(n)
                        start.append(a)
                        length.append(min(capacity, total - a))
                        crc.append(zlib.crc32(ids[4 * a : 4 * (a + capacity)]))
                    n += 1
            start = np.array(start, dtype=np.int64)
            yield pd.DataFrame({"doc_id": df["doc_id"].astype("Int64").iloc[which].reset_index(drop=True), "piece": (start // capacity).astype(np.int32), "start": start, "length": np.array(length, dtype=np.int32), "ids_crc32": np.array(crc, dtype=np.int64)})

    return docs.select("doc_id", "text").mapInPandas(run, PIECE_SCHEMA)


def heaviest(weight: np.ndarray, limit: np.ndarray, units: int) -> np.ndarray:
    """Knapsack by dynamic programming: how many of each class (class c takes c units) the heaviest configuration within `units` has.

    weight and limit are indexed by class; a class with limit 0 is left out. A configuration that
    exceeds a limit is cut back to it.
    """
    classes = np.flatnonzero(limit > 0)
    if not len(classes):
        return np.zeros(len(weight), dtype=np.int64)
    small = [(c, float(weight[c])) for c in classes.tolist() if c < BLOCK]
    value = np.full(units + 1, -np.inf)
    value[classes] = weight[classes]
    value[:BLOCK] = -np.inf
    # back[units - c] for c units, -inf after: row i of a block's view is what lies below lo + i, by class.
    # What large classes give within a block depends on what lies before it alone; small ones go unit by unit
    back = np.full(2 * units + 1, -np.inf)
    back[units] = last = 0.0
    near = [-np.inf] * (BLOCK - 1) + [0.0]
    take = [0] * (units + 1)
    for lo in range(1, units + 1, BLOCK):
        n = min(BLOCK, units + 1 - lo)
        below = as_strided(back[units - lo :], (n, lo + n), (-back.strides[0], back.strides[0]), writeable=False)
        gain = below + value[: lo + n]
        whose = gain.argmax(axis=1)
        tops = gain[np.arange(n), whose].tolist()
        for i, (top, own) in enumerate(zip(tops, whose.tolist(), strict=True)):
            most, which = -np.inf, 0
            for c, v in small:
                if near[BLOCK + i - c] + v > most:
                    most, which = near[BLOCK + i - c] + v, c
            if top > most:
                most, which = top, own
            if most > last:
                last, take[lo + i] = most, which
            near.append(last)
        back[units - lo - n + 1 : units - lo + 1] = near[: BLOCK - 1 : -1]
        near = near[-BLOCK:]
    out, c = np.zeros(len(weight), dtype=np.int64), units
    while c > 0:
        if take[c]:
            out[take[c]] += 1
            c -= take[c]
        else:
            c -= 1
    return np.minimum(out, limit)


def configurations(counts: np.ndarray, units: int, *, eta: float = 2.0, step: float = 0.5) -> tuple[list[tuple[np.ndarray, float]], float]:
    """A fractional solution of the covering program, and a lower bound of its value.

    Solution: (configuration, times) whose sum covers counts exactly. Weights (the prices of the
    classes) start at the classes' sizes. Each round prices out the heaviest configuration by
    knapsack, takes it until some class of it has gained `step` of its count or is covered, and
    multiplies the weight of what it covers by exp(-eta * share covered); covered classes weigh
    nothing. A configuration that comes back adds to its times, so the solution is the average of
    the rounds. Prices over the heaviest configuration's weight are a feasible dual solution of
    every round; the best one is the bound. A round brings a class on by `step` or to its end, so
    there are at most classes / step rounds.
    """
    n = counts.astype(float)
    weight = np.where(counts > 0, np.arange(len(counts), dtype=float), 0.0)
    left = n.copy()
    times: dict[bytes, float] = {}
    bound = 0.0
    while (open_ := left > 0).any():
        a = heaviest(weight, np.where(open_, units, 0), units)
        bound = max(bound, float(weight @ n) / float(weight @ a))
        used = np.flatnonzero(a)
        t = float((np.minimum(step * n[used], left[used]) / a[used]).min())
        times[a.tobytes()] = times.get(a.tobytes(), 0.0) + t
        left[used] -= t * a[used]
        left[left < 1e-9 * np.maximum(1, n)] = 0
        weight[used] *= np.exp(-eta * t * a[used] / n[used])
        weight[left == 0] = 0
    return [(np.frombuffer(k, dtype=np.int64), t) for k, t in times.items()], bound


@dataclass
class PackingPlan:
    """Where the k-th item of each class goes. Items of a class are numbered by length, then by place.

    runs[c]: rows (first item, items per sequence, first sequence, first slot) for the rounded
    configurations, sorted; rest_from[c]: the first item placed one by one; rest[c]: its rows
    (sequence, slot). base[length]: number of the first item of that length in its class.
    lower_bound: no packing has fewer sequences, by tokens alone; program_bound: the dual bound of
    the program on the classes, whose lengths are rounded up.
    """

    runs: dict[int, np.ndarray]
    rest_from: np.ndarray
    rest: dict[int, np.ndarray]
    base: np.ndarray
    sequences: int
    lower_bound: int
    program_bound: float

    @property
    def gap(self) -> float:
        """Sequences above the token bound, as a share of it."""
        return self.sequences / self.lower_bound - 1 if self.lower_bound else 0.0


def class_of(length, unit: int = UNIT):
    return -(-length // unit)


def plan(histogram: dict[int, int], *, capacity: int = CAPACITY, unit: int = UNIT) -> PackingPlan:
    """Pack a histogram {length: items}; lengths over the capacity are an error."""
    hist = np.zeros(capacity + 1, dtype=np.int64)
    for length, n in histogram.items():
        if not 0 < length <= capacity:
            raise ValueError(f"length {length} does not fit a sequence of {capacity}")
        hist[length] = n
    units = capacity // unit
    lengths = np.arange(capacity + 1)
    cls = class_of(lengths, unit)
    counts = np.bincount(cls, weights=hist, minlength=units + 1).astype(np.int64)[: units + 1]
    before = np.cumsum(hist) - hist
    base = before - before[np.maximum(0, (cls - 1) * unit + 1)]
    base[0] = 0
    used = np.zeros(units + 1, dtype=np.int64)
    runs: dict[int, list] = {}
    seq = 0
    solution, program_bound = configurations(counts, units)
    for a, times in sorted(solution, key=lambda x: -x[1]):
        t = int(times + 1e-9)
        if not t:
            continue
        slot = 0
        for c in np.flatnonzero(a).tolist():
            runs.setdefault(c, []).append((used[c], a[c], seq, slot))
            used[c] += t * a[c]
            slot += int(a[c])
        seq += t
    # what rounding has left, longest first, into the fullest sequence that still takes it
    rest: dict[int, list] = {c: [] for c in np.flatnonzero(counts > used).tolist()}
    room: list[tuple[int, int]] = []  # (free tokens, sequence), sorted
    slots: dict[int, int] = {}
    todo = []
    for c in rest:
        cum = np.cumsum(hist[(c - 1) * unit + 1 : c * unit + 1])
        items = np.searchsorted(cum, np.arange(used[c], counts[c]), side="right") + (c - 1) * unit + 1
        rest[c] = [None] * len(items)
        todo += [(int(x), c, k) for k, x in enumerate(items)]
    for length, c, k in sorted(todo, reverse=True):
        at = bisect_left(room, (length, -1))
        free, s = room.pop(at) if at < len(room) else (capacity, seq)
        if s == seq:
            seq += 1
        rest[c][k] = (s, slots.get(s, 0))
        slots[s] = slots.get(s, 0) + 1
        if free > length:
            insort(room, (free - length, s))
    total = int((hist * lengths).sum())
    return PackingPlan({c: np.array(r, dtype=np.int64) for c, r in runs.items()}, used, {c: np.array(r, dtype=np.int64).reshape(-1, 2) for c, r in rest.items()}, base, seq, -(-total // capacity), program_bound)


def place(p: PackingPlan, length: np.ndarray, rank: np.ndarray, unit: int = UNIT) -> tuple[np.ndarray, np.ndarray]:
    """Sequence and slot of items given by length and number among the items of that length."""
    cls, item = class_of(length, unit), rank + p.base[length]
    seq, slot = np.empty(len(length), dtype=np.int64), np.empty(len(length), dtype=np.int64)
    for c in np.unique(cls).tolist():
        m = np.flatnonzero(cls == c)
        k = item[m]
        late = k >= p.rest_from[c]
        if late.any():
            r = p.rest[c][k[late] - p.rest_from[c]]
            seq[m[late]], slot[m[late]] = r[:, 0], r[:, 1]
        if not late.all():
            runs, k = p.runs[c], k[~late]
            r = runs[np.searchsorted(runs[:, 0], k, side="right") - 1]
            seq[m[~late]] = r[:, 2] + (k - r[:, 0]) // r[:, 1]
            slot[m[~late]] = r[:, 3] + (k - r[:, 0]) % r[:, 1]
    return seq, slot


def pack(parts: DataFrame, *, capacity: int = CAPACITY, unit: int = UNIT) -> DataFrame:
    """Rows with an int column `length` get sequence_id, and offset within it (gapless from 0).

    Two passes over small rows: the histogram (at most `capacity` rows reach the driver), then the
    placement. Rows are numbered within (file, length), so a length that a third of all rows
    share is still numbered by as many tasks as there are files. Empty table: empty result. Equal
    rows are packed once each. Old columns sequence_id and offset are replaced; others pass.
    """
    spark, cols = parts.sparkSession, [c for c in parts.columns if c.lower() not in ("sequence_id", "offset")]
    parts = parts.select(*[F.col(f"`{c}`") for c in cols])
    stored = keep(parts, workspace(spark, "pieces"))
    stored = stored.select("*", stored.metadataColumn("_metadata").getField("file_path").alias("__file"), stored.metadataColumn("_metadata").getField("row_index").alias("__row"))
    per_file = stored.groupBy("__file", "length").agg(F.count("*").alias("__n"))
    histogram = {r[0]: r[1] for r in stored.groupBy("length").count().collect()}  # at most `capacity` rows
    p = plan(histogram, capacity=capacity, unit=unit)
    first = per_file.withColumn("__first", F.sum("__n").over(Window.partitionBy("length").orderBy("__file").rowsBetween(Window.unboundedPreceding, -1))).select("__file", "length", F.coalesce("__first", F.lit(0)).alias("__first"))
    ranked = stored.withColumn("__rank", F.row_number().over(Window.partitionBy("__file", "length").orderBy("__row")) - 1).join(first, ["__file", "length"]).withColumn("__rank", F.col("__rank") + F.col("__first"))

    @F.pandas_udf("seq long, slot long")
    def where(length: pd.Series, rank: pd.Series) -> pd.DataFrame:
        seq, slot = place(p, length.to_numpy(np.int64), rank.to_numpy(np.int64), unit)
        return pd.DataFrame({"seq": seq, "slot": slot})

    put = ranked.withColumn("__at", where("length", "__rank"))
    inside = Window.partitionBy("__at.seq").orderBy("__at.slot").rowsBetween(Window.unboundedPreceding, -1)  # a sequence has at most `capacity` rows
    return put.select(*[F.col(f"`{c}`") for c in cols], F.col("__at.seq").alias("sequence_id"), F.coalesce(F.sum("length").over(inside), F.lit(0)).cast("long").alias("offset"))


def op10(spark, sf_dir: str) -> DataFrame:
    from llm.store import table

    out = pack(pieces(table(spark, sf_dir, "documents")))
    return out.withColumn("length", F.col("length").cast("long"))
