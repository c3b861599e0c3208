"""Repeated passages: every byte covered by a string of LENGTH bytes that also starts elsewhere.

Sorting all suffixes of a corpus would move it many times over. Instead each text is sampled at
anchors that depend on content only: in each run of LENGTH bytes the GRAM-byte string of the
smallest hash. Two equal runs have equal anchors at equal places, so a repeat shows as two
anchors with the same gram, and only around those the text is looked at.

Around each shared anchor the suffixes are sorted by a mergesort whose comparisons are made on
prefix polynomial hashes: a binary search finds the length of the common extension, so comparing
two suffixes takes a logarithmic number of steps. Neighbours in that order give the common
extensions to the right, hashes of the bytes before the anchor those to the left; what they call
equal is verified byte by byte.

Places whose whole contexts are equal need no sort: a context is named by 128 bits of a
cryptographic digest of its bytes, and one that occurs twice repeats as a whole. An anchor that
very many different contexts share is not gathered in a task: its windows are counted by two
64-bit hashes.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from llm.store import drop, fresh, keep, release, table, workspace
from llm.textkit import U64, PrefixHash, mix64, tidy

LENGTH = 200
GRAM = 64
#: Places of one anchor that a single task compares; an anchor with more is counted window by window.
HOT = 50_000
#: Bytes of text in one numpy pass.
BATCH_BYTES = 1 << 20


def _sliding(x: np.ndarray, w: int, op) -> np.ndarray:
    """op (np.minimum or np.maximum) over every w neighbouring values, by running values from both ends of blocks of w."""
    n = len(x) - w + 1
    if n <= 0:
        return x[:0]
    edge = np.iinfo(x.dtype).max if op is np.minimum else 0
    rows = np.concatenate([x, np.full(-len(x) % w, edge, dtype=x.dtype)]).reshape(-1, w)
    ahead = op.accumulate(rows, axis=1).ravel()
    behind = op.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return op(behind[:n], ahead[w - 1 : w - 1 + n])


def anchors(buf: np.ndarray, offsets: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Anchors of the texts buf[offsets[i]:offsets[i+1]]; texts under `length` bytes have none.

    Returns their places in buf, gram hashes, digests of their contexts (up to length - gram bytes
    before the place, up to length from it on; 128 bits as two numbers), and the two reaches of
    these contexts.
    """
    span = length - gram + 1
    n = len(buf) - gram + 1
    none = np.zeros(0, np.int64)
    if n < span:
        return none, none.astype(U64), none.reshape(0, 1).repeat(2, axis=1), none, none
    at = np.arange(n)
    sums = PrefixHash(buf)
    h = mix64(sums.raw(at, at + gram)) | U64(1)
    size = np.diff(offsets)
    left = np.repeat(offsets[1:], size)[:n] - at  # bytes from here to the text's end
    h[left < gram] = np.iinfo(U64).max
    low = _sliding(h, span, np.minimum)
    low[left[: len(low)] < length] = 0  # no run of this length starts here
    pad = np.zeros(span - 1, dtype=U64)
    high = _sliding(np.concatenate([pad, low, pad]), span, np.maximum)[:n]
    place = np.flatnonzero((h == high) & (left >= gram))
    first = np.repeat(offsets[:-1], size)[place]
    reach, ahead = np.minimum(place - first, span - 1), np.minimum(left[place], length)
    raw, digest = memoryview(buf), hashlib.blake2b
    names = b"".join([digest(raw[a:b], digest_size=16, salt=c.to_bytes(2)).digest() for a, b, c in zip((place - reach).tolist(), (place + ahead).tolist(), reach.tolist(), strict=True)])
    return place, h[place], np.frombuffer(names, dtype="<i8").reshape(-1, 2), reach, ahead


def _raw(text) -> bytes:
    return text.encode("utf-8", "surrogatepass") if isinstance(text, str) else b""


def _batches(raw: list[bytes]):
    start, size = 0, 0
    for i, r in enumerate(raw):
        if i > start and size + len(r) > BATCH_BYTES:
            yield start, i
            start, size = i, 0
        size += len(r)
    if len(raw) > start:
        yield start, len(raw)


def find_anchors(keyed: DataFrame) -> DataFrame:
    """(k1, k2, pos, reach, ahead, h, cx, cy) for each anchor of each text."""

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for df in batches:
            raw, k1, k2 = [_raw(t) for t in df["text"]], df["k1"].to_numpy(), df["k2"].to_numpy()
            for a, b in _batches(raw):
                offsets = np.concatenate(([0], np.cumsum([len(r) for r in raw[a:b]])))
                place, h, cx, reach, ahead = anchors(np.frombuffer(b"".join(raw[a:b]), dtype=np.uint8), offsets)
                who = np.searchsorted(offsets, place, side="right") - 1
                yield pd.DataFrame({"k1": k1[a:b][who], "k2": k2[a:b][who], "pos": (place - offsets[who]).astype(np.int32), "reach": reach.astype(np.int16), "ahead": ahead.astype(np.int16), "h": h.view(np.int64), "cx": cx[:, 0], "cy": cx[:, 1]})

    return keyed.where(f"octet_length(text) >= {LENGTH}").select("k1", "k2", "text").mapInPandas(run, "k1 long, k2 long, pos int, reach short, ahead short, h long, cx long, cy long")


CONTEXT = "h long, hot boolean, k1 long, k2 long, pos int, reach int, around binary"


def contexts(marked: DataFrame) -> DataFrame:
    """The bytes around each anchor in `marks`: up to LENGTH - GRAM before it (reach of them) and LENGTH from it on."""

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for df in batches:
            h, hot, k1s, k2s, poss, reach, around = ([] for _ in range(7))
            for k1, k2, text, marks in zip(df["k1"], df["k2"], df["text"], df["marks"], strict=True):
                raw = _raw(text)
                for m in marks:
                    pos = m["pos"]
                    start = max(0, pos - (LENGTH - GRAM))
                    h.append(m["h"])
                    hot.append(m["hot"])
                    poss.append(pos)
                    reach.append(pos - start)
                    around.append(raw[start : pos + LENGTH])
                k1s += [k1] * len(marks)
                k2s += [k2] * len(marks)
            yield pd.DataFrame({"h": h, "hot": hot, "k1": k1s, "k2": k2s, "pos": poss, "reach": reach, "around": around})

    return marked.mapInPandas(run, CONTEXT)


class Suffixes:
    """Suffixes of a buffer, each from start to end, compared by prefix hashes."""

    def __init__(self, buf: np.ndarray, rows: np.ndarray, start: np.ndarray, end: np.ndarray):
        self.buf, self.start, self.end = buf, start, end
        self.hash = PrefixHash(buf, rows)

    def common(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of the common beginning of suffixes i and j, by binary search on hashes."""
        a, b = self.start[i], self.start[j]
        low, high = np.zeros(len(i), dtype=np.int64), np.minimum(self.end[i] - a, self.end[j] - b)
        for _ in range(int(high.max(initial=0)).bit_length()):
            mid = (low + high + 1) >> 1
            same = self.hash.raw(a, a + mid) == self.hash.raw(b, b + mid)
            low, high = np.where(same, mid, low), np.where(same, high, mid - 1)
        return low

    def before(self, i: np.ndarray, j: np.ndarray, or_equal: bool) -> np.ndarray:
        """Whether suffix i sorts before j (or is equal to it)."""
        n = self.common(i, j)
        left, right = self.end[i] - self.start[i] - n, self.end[j] - self.start[j] - n
        both = (left > 0) & (right > 0)
        ci, cj = self.buf[np.where(both, self.start[i] + n, 0)], self.buf[np.where(both, self.start[j] + n, 0)]
        return np.where(both, ci < cj, (left < right) | (or_equal & (left == right)))

    def order(self, group: np.ndarray) -> np.ndarray:
        """Suffix numbers sorted within their groups (group is ascending): a mergesort of all groups at once.

        In each round two neighbouring runs of a group become one; an element's place is its own
        place in its run plus the number of elements of the other run before it, which a binary
        search finds.
        """
        n = len(group)
        item = np.arange(n)
        first = np.concatenate(([0], np.flatnonzero(group[1:] != group[:-1]) + 1))
        begin = np.repeat(first, np.diff(np.append(first, n)))
        stop = np.repeat(np.append(first[1:], n), np.diff(np.append(first, n)))
        largest = int((stop - begin).max(initial=0))
        width = 1
        while width < largest:
            at = np.arange(n) - begin
            block = begin + at // (2 * width) * (2 * width)
            middle, last = np.minimum(block + width, stop), np.minimum(block + 2 * width, stop)
            act = np.flatnonzero(middle < last)
            on_left = np.arange(n)[act] < middle[act]
            low = np.where(on_left, middle[act], block[act])
            base, high = low.copy(), np.where(on_left, last[act], middle[act])
            while (todo := np.flatnonzero(low < high)).size:
                mid = (low[todo] + high[todo]) >> 1
                # how many of the other run go first: smaller ones, and equal ones of the left run
                first_ = self.before(item[mid], item[act[todo]], False) | (~on_left[todo] & self._equal(item[mid], item[act[todo]]))
                low[todo] = np.where(first_, mid + 1, low[todo])
                high[todo] = np.where(first_, high[todo], mid)
            place = np.arange(n)
            place[act] = np.where(on_left, act + (low - base), block[act] + (act - middle[act]) + (low - base))
            out = np.empty(n, dtype=item.dtype)
            out[place] = item
            item = out
            width *= 2
        return item

    def _equal(self, i, j):
        n = self.end[i] - self.start[i]
        return (n == self.end[j] - self.start[j]) & (self.hash.raw(self.start[i], self.start[i] + np.minimum(n, self.end[j] - self.start[j])) == self.hash.raw(self.start[j], self.start[j] + np.minimum(n, self.end[j] - self.start[j])))


def repeated_starts(group: np.ndarray, around: list[bytes], reach: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> np.ndarray:
    """For each context (rows of a group stand together) a row of booleans: whether the run that starts j bytes before the anchor occurs in another context of the group."""
    span = length - gram + 1
    n = len(around)
    marks = np.zeros((n, span), dtype=bool)
    if n < 2:
        return marks
    sizes = np.array([len(x) for x in around], dtype=np.int64)
    base = np.cumsum(sizes) - sizes
    buf = np.frombuffer(b"".join(around), dtype=np.uint8)
    anchor, end = base + reach, base + sizes
    s = Suffixes(buf, base, anchor, end)
    order = s.order(group)
    same = group[order[1:]] == group[order[:-1]]
    shared = np.zeros(n + 1, dtype=np.int64)  # with the one before, in order
    if same.any():
        k = np.flatnonzero(same) + 1
        shared[k] = s.common(order[k - 1], order[k])
    best = np.maximum(shared[:-1], shared[1:])
    ahead = sizes - reach
    xs, ys, js = [], [], []

    def settle():
        """Compare byte by byte what the hashes call equal, once for each pair, and mark what is."""
        x, y, j = np.concatenate(xs), np.concatenate(ys), np.concatenate(js)
        for held in (xs, ys, js):
            held.clear()
        pair, of = np.unique(x * n + y, return_inverse=True)
        left, right = common_bytes(buf, base, anchor, end, pair // n, pair % n, span - 1, length)
        true = (left[of] >= j) & (right[of] >= length - j)
        marks[x[true], j[true]] = marks[y[true], j[true]] = True
        for row, at in {(int(r), int(k)) for r, k in [*zip(x[~true], j[~true], strict=True), *zip(y[~true], j[~true], strict=True)]}:
            a = int(reach[row]) - at  # a collision: against all of the group
            mine = around[row][a : a + length]
            marks[row, at] = any(r != row and reach[r] >= at and around[r][int(reach[r]) - at :][:length] == mine for r in np.flatnonzero(group == group[row]).tolist())

    for j in range(span):
        need = length - j
        rows = np.flatnonzero(best >= need)
        who = order[rows]
        ok = (reach[who] >= j) & (ahead[who] >= need)
        rows, who = rows[ok], who[ok]
        if len(who) < 2:
            continue
        run = np.cumsum(shared[:-1] < need)
        key = mix64(run[rows].astype(U64)) ^ mix64(s.hash.raw(anchor[who] - j, anchor[who]) + U64(1))
        by = np.argsort(key)
        eq = np.flatnonzero(key[by[1:]] == key[by[:-1]])
        if len(eq):
            xs.append(who[by[eq + 1]])
            ys.append(who[by[eq]])
            js.append(np.full(len(eq), j, dtype=np.int64))
        if sum(map(len, xs)) > 200_000:
            settle()
    if xs:
        settle()
    return marks


def common_bytes(buf, base, anchor, end, x, y, before: int, after: int, rows: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """Equal bytes of contexts x and y before their anchors (up to `before`) and from there on (up to `after`)."""
    left, right = np.empty(len(x), dtype=np.int64), np.empty(len(x), dtype=np.int64)
    back, on = -1 - np.arange(before), np.arange(after)
    for a in range(0, len(x), rows):
        p, q = x[a : a + rows], y[a : a + rows]
        for out, step, room in ((left, back, np.minimum(anchor[p] - base[p], anchor[q] - base[q])), (right, on, np.minimum(end[p] - anchor[p], end[q] - anchor[q]))):
            i, j = (np.clip(anchor[r][:, None] + step, 0, len(buf) - 1) for r in (p, q))
            differ = (buf[i] != buf[j]) | (np.arange(len(step)) >= room[:, None])
            out[a : a + rows] = np.where(differ.any(axis=1), differ.argmax(axis=1), len(step))
    return left, right


SPANS = "k1 long, k2 long, start int, stop int"


def spans_of(df: pd.DataFrame) -> pd.DataFrame:
    """Repeated spans found in whole groups of contexts (sorted by h)."""
    group, around = df["h"].to_numpy(), df["around"].tolist()
    reach, pos = df["reach"].to_numpy().astype(np.int64), df["pos"].to_numpy().astype(np.int64)
    marks = repeated_starts(group, around, reach)
    edge = np.diff(np.pad(marks.astype(np.int8), ((0, 0), (1, 1))), axis=1)
    row, low = np.nonzero(edge == 1)
    _, high = np.nonzero(edge == -1)
    return pd.DataFrame({"k1": df["k1"].to_numpy()[row], "k2": df["k2"].to_numpy()[row], "start": (pos[row] - high + 1).astype(np.int32), "stop": (pos[row] - low + LENGTH).astype(np.int32)})


def compare_groups(found: DataFrame, rows: int = 4000) -> DataFrame:
    """Spans of all anchors that are not hot: contexts are dealt and sorted by anchor, whole groups are compared together, at least `rows` contexts at a time."""

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        count = 0
        for df in batches:
            held.append(df)
            count += len(df)
            if count >= rows:
                df = pd.concat(held, ignore_index=True)
                h = df["h"].to_numpy()
                cut = int(np.searchsorted(h, h[-1]))  # the last group may go on
                if cut:
                    yield spans_of(df.iloc[:cut])
                held, count = [df.iloc[cut:]], len(df) - cut
        if count:
            yield spans_of(pd.concat(held, ignore_index=True))

    return found.where("not hot").repartition("h").sortWithinPartitions("h").mapInPandas(run, SPANS)


def count_windows(found: DataFrame) -> DataFrame:
    """Spans of hot anchors: every run around them is hashed to 128 bits and counted, with partial sums where it is made."""
    hot = found.where("hot")

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for whole in batches:
            for a in range(0, len(whole), 256):  # each row makes up to LENGTH - GRAM + 1
                df = whole.iloc[a : a + 256]
                sizes = df["around"].map(len).to_numpy()
                many = np.maximum(0, sizes - LENGTH + 1)
                base = np.repeat(np.cumsum(sizes) - sizes, many)
                row = np.repeat(np.arange(len(df)), many)
                off = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
                buf = np.frombuffer(b"".join(df["around"]), dtype=np.uint8)
                w1 = PrefixHash(buf).raw(base + off, base + off + LENGTH)
                w2 = PrefixHash(buf[::-1]).raw(len(buf) - base - off - LENGTH, len(buf) - base - off)
                first = (df["pos"] - df["reach"]).to_numpy()
                yield pd.DataFrame({"w1": mix64(w1).view(np.int64), "w2": mix64(w2).view(np.int64), "k1": df["k1"].to_numpy()[row], "k2": df["k2"].to_numpy()[row], "start": (first[row] + off).astype(np.int32)})

    windows = hot.mapInPandas(run, "w1 long, w2 long, k1 long, k2 long, start int")
    again = windows.groupBy("w1", "w2").agg(F.min(F.struct("k1", "k2", "start")).alias("a"), F.max(F.struct("k1", "k2", "start")).alias("b")).where("a <> b").select("w1", "w2")
    return windows.join(again, ["w1", "w2"]).select("k1", "k2", "start", (F.col("start") + LENGTH).alias("stop"))


def _keyed(docs: DataFrame, k1: str = "k1", k2: str = "k2") -> DataFrame:
    """Two hashes that name a row by its id and text; equal rows share them, which does no harm."""
    return docs.withColumn(k1, F.xxhash64("doc_id", "text")).withColumn(k2, F.xxhash64(F.lit(7), "text", "doc_id"))


def repeated_spans(docs: DataFrame, path: str) -> DataFrame:
    """(k1, k2, spans) of every text with repeats: overlapping (start, stop) byte spans."""
    spark = docs.sparkSession
    keyed = _keyed(docs.select("doc_id", "text"))
    found = keep(find_anchors(keyed), f"{path}/anchors")
    # tables by key are written before they are joined: both sides of the join are then plain shuffles, and a hot key is split
    name = F.struct("cx", "cy")
    often = keep(found.groupBy("h").agg(F.count("*").alias("n"), (F.min(name) != F.max(name)).alias("mixed")).where("n > 1").select("h", "mixed"), f"{path}/often")
    shared = keep(found.join(often, "h"), f"{path}/shared")
    drop(spark, f"{path}/anchors")
    release(spark)
    # a context that occurs twice repeats as a whole, and only its first place is compared further
    place = F.struct("k1", "k2", "pos")
    times = keep(shared.where("mixed").groupBy("h", "cx", "cy").agg(F.count("*").alias("times"), F.min(place).alias("first")), f"{path}/times")
    rated = keep(shared.where("mixed").join(times, ["h", "cx", "cy"]).withColumn("sent", place == F.col("first")).drop("first"), f"{path}/rated")
    whole = shared.where("not mixed").select("k1", "k2", "pos", "reach", "ahead").unionByName(rated.where("times > 1").select("k1", "k2", "pos", "reach", "ahead"))
    whole = whole.select("k1", "k2", (F.col("pos") - F.col("reach")).cast("int").alias("start"), (F.col("pos") + F.col("ahead")).cast("int").alias("stop")).where(F.col("stop") - F.col("start") >= LENGTH)
    crowds = keep(rated.where("sent").groupBy("h").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("h", F.lit(True).alias("hot")), f"{path}/crowds")
    sent = rated.where("sent").join(crowds, "h", "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
    marks = keep(sent.groupBy("k1", "k2").agg(F.collect_set(F.struct("pos", "h", "hot")).alias("marks")), f"{path}/marks")
    release(spark)
    around = contexts(keyed.where(f"octet_length(text) >= {LENGTH}").join(marks, ["k1", "k2"]))
    parts = [compare_groups(around)]
    if crowds.limit(1).count():
        parts.append(count_windows(around))
    compared = [keep(p, f"{path}/part{i}") for i, p in enumerate(parts)]
    release(spark)
    spans = reduce(DataFrame.unionByName, compared, whole)
    out = keep(spans.groupBy("k1", "k2").agg(F.collect_set(F.struct("start", "stop")).alias("spans")), f"{path}/spans")
    drop(spark, *(f"{path}/{t}" for t in ("often", "shared", "times", "rated", "crowds", "marks", "part0", "part1")))
    release(spark)
    return out


def merge(spans) -> list[tuple[int, int]]:
    """Maximal runs of covered bytes."""
    out: list[list[int]] = []
    for a, b in sorted((s["start"], s["stop"]) for s in spans) if spans is not None and len(spans) else []:
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def cut(raw: bytes, runs: list[tuple[int, int]]) -> bytes:
    at, kept = 0, []
    for a, b in runs:
        kept.append(raw[at:a])
        at = b
    return b"".join([*kept, raw[at:]])


def with_spans(docs: DataFrame, path: str | None = None, out: str = "__spans") -> DataFrame:
    """Every row of docs with its spans in column `out` (null where nothing repeats). Null texts count as empty; other columns of docs may have any names but `out`."""
    spans = repeated_spans(docs, path or workspace(docs.sparkSession, "suffix"))
    k1, k2 = fresh(docs, "__k1"), fresh(docs, "__k2")
    return _keyed(docs, k1, k2).join(spans.select(F.col("k1").alias(k1), F.col("k2").alias(k2), F.col("spans").alias(out)), [k1, k2], "left").drop(k1, k2)


def measure(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for each row."""

    @F.pandas_udf("n_bytes long, n_removed long, n_spans long, kept_sha256 string")
    @tidy
    def look(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        for texts, spans in batches:
            rows = []
            for t, s in zip(texts, spans, strict=True):
                raw, runs = _raw(t), merge(s)
                rest = cut(raw, runs)
                rows.append((len(raw), len(raw) - len(rest), len(runs), hashlib.sha256(rest).hexdigest()))
            yield pd.DataFrame(rows, columns=["n_bytes", "n_removed", "n_spans", "kept_sha256"])

    return with_spans(docs.select("doc_id", "text")).select("doc_id", look("text", "__spans").alias("m")).select("doc_id", "m.*")


def remove_repeats(docs: DataFrame) -> DataFrame:
    """All rows and columns of docs; from text every repeated passage is cut (bytes of a character cut in half go too), and n_chars, if there, counts what is left."""

    @F.pandas_udf("string")
    @tidy
    def strip(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for texts, spans in batches:
            yield pd.Series([cut(_raw(t), merge(s)).decode("utf-8", "ignore") if s is not None else t for t, s in zip(texts, spans, strict=True)])

    spans = fresh(docs, "__spans")
    out = with_spans(docs, out=spans).withColumn("text", strip("text", spans)).drop(spans)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.coalesce(F.length("text").cast(docs.schema["n_chars"].dataType), "n_chars"))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def op2(spark, sf_dir: str) -> DataFrame:
    return measure(table(spark, sf_dir, "documents"))
