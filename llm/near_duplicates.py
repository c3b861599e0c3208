"""Near-duplicate documents by HyperMinHash.

A document's distinct five-word shingles are hashed once; the first bits of a hash choose one of
128 buckets and the bucket keeps the smallest rest, compressed to a count of leading zeros and a
few mantissa bits. Bands of these compressed registers bring similar documents together; a
collision-corrected estimate of the Jaccard similarity rejects most false candidates, and every
link is confirmed on the full shingle sets.

Documents with equal sets are one class from the start, so the largest groups of copies cost one
row each. Inside a band's bucket no pairs are listed: every class is compared with the bucket's
centre, and only buckets that still hold more than one component afterwards are searched fully,
in blocks of bounded size, for links between components: by registers first, and then, for the
rows that these leave, on the full sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from llm.store import drop, fresh, keep, release, table, workspace
from llm.textkit import U64, mix64, shingle_hashes, text_batches, tidy

BUCKET_BITS = 7
BUCKETS = 1 << BUCKET_BITS
MANTISSA_BITS = 10
BANDS, ROWS = 24, 5
#: Links of op1: 100 * intersection >= LINK_PERCENT * union.
LINK_PERCENT = 85
#: How far below the threshold an estimate may fall and still be verified: five standard errors of 128 registers.
ESTIMATE_SLACK = 0.16
#: Classes in one block of the full search of a bucket.
BLOCK = 512

_BOUNDS = np.arange(BUCKETS, dtype=U64) << U64(64 - BUCKET_BITS)


def _detours(seed: int = 17) -> np.ndarray:
    """For each bucket the order in which an empty one asks the others for a value; itself first."""
    rng = np.random.default_rng(seed)
    return np.array([[b, *rng.permutation(np.delete(np.arange(BUCKETS), b))] for b in range(BUCKETS)])


_DETOURS = _detours()


def compress(rest: np.ndarray) -> np.ndarray:
    """Leading zeros (6 bits) and the mantissa behind the leading one, of 53-bit numbers, as uint16. Keeps the order of equal exponents only, as registers need."""
    mantissa, exponent = np.frexp(rest.astype(np.float64))
    zeros = np.where(rest > 0, 53 - exponent, 53).astype(np.int64)
    digits = np.where(rest > 0, ((mantissa * 2 - 1) * (1 << MANTISSA_BITS)), 0).astype(np.int64)
    return (zeros << MANTISSA_BITS | digits).astype("<u2")


def registers(sets: list[np.ndarray]) -> np.ndarray:
    """One row of BUCKETS registers for each non-empty sorted set. An empty bucket takes the value of the first filled one on its detour, so that small sets have full bands too."""
    rest = np.empty((len(sets), BUCKETS), dtype=U64)
    for i, s in enumerate(sets):
        at = np.searchsorted(s, _BOUNDS)
        filled = np.append(at[1:], len(s)) > at
        if not filled.all():
            at = at[_DETOURS[np.arange(BUCKETS), filled[_DETOURS].argmax(axis=1)]]
        rest[i] = s[at] << U64(BUCKET_BITS)
    return compress(rest >> U64(11))


def band_keys(regs: np.ndarray) -> np.ndarray:
    """A 64-bit key for each row and band."""
    k = np.zeros((len(regs), BANDS), dtype=U64)
    for r in range(ROWS):
        k = mix64(k ^ (regs[:, r : BANDS * ROWS : ROWS].astype(U64) + U64(1 + r * 0x10000)) + np.arange(BANDS, dtype=U64) * U64(0x9E3779B97F4A7C15))
    return k.view(np.int64)


def estimate(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Jaccard estimates of register rows, corrected for registers that are equal by chance.

    Two unequal minima agree in exponent (1/3, two geometric counts) and in MANTISSA_BITS more bits.
    """
    equal = (a == b).mean(axis=-1)
    chance = 1 / (3 * (1 << MANTISSA_BITS))
    return np.clip((equal - chance) / (1 - chance), 0, 1)


def fingerprint(s: np.ndarray) -> bytes:
    """128 bits of a set: two sums of independently mixed elements, and so independent of order."""
    return np.array([mix64(s).sum(dtype=U64), mix64(s ^ U64(0xA5A5A5A55A5A5A5A)).sum(dtype=U64)], dtype=U64).tobytes()


PROFILE = "doc_id long, n_shingles long, fp binary, regs binary"


def profiles(docs: DataFrame) -> DataFrame:
    """Set size, fingerprint and registers of each document; no fingerprint for an empty set."""

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for df in batches:
            texts = df["text"].tolist()
            for part in text_batches(texts):
                sets = shingle_hashes(texts[part])
                full = [i for i, s in enumerate(sets) if len(s)]
                regs = registers([sets[i] for i in full])
                fp, rg = [None] * len(sets), [None] * len(sets)
                for row, i in enumerate(full):
                    fp[i], rg[i] = fingerprint(sets[i]), regs[row].tobytes()
                yield pd.DataFrame({"doc_id": df["doc_id"].iloc[part].astype("Int64").to_numpy(object), "n_shingles": [len(s) for s in sets], "fp": fp, "regs": rg})

    return docs.select("doc_id", "text").mapInPandas(run, PROFILE)


def bands_of(classes: DataFrame) -> DataFrame:
    """(key, id) for each class and band."""

    @F.pandas_udf("array<long>")
    def keys(regs: pd.Series) -> pd.Series:
        return pd.Series(list(band_keys(np.frombuffer(b"".join(regs), dtype="<u2").reshape(-1, BUCKETS)))) if len(regs) else pd.Series([], dtype=object)

    return classes.select("id", F.explode(keys("regs")).alias("key"))


def _linked(a: np.ndarray, b: np.ndarray, percent: int = LINK_PERCENT) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def confirm(pairs: DataFrame, percent: int = LINK_PERCENT) -> DataFrame:
    """Pairs (a, b) with regs and texts of both sides that are links: estimated first, then confirmed on the full sets."""

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for df in batches:
            if not len(df):
                continue
            ra, rb = (np.frombuffer(b"".join(df[c]), dtype="<u2").reshape(-1, BUCKETS) for c in ("regs_a", "regs_b"))
            df = df[estimate(ra, rb) >= percent / 100 - ESTIMATE_SLACK]
            memo: dict[int, np.ndarray] = {}
            ok = []
            for a, b, ta, tb in zip(df["a"], df["b"], df["text_a"], df["text_b"], strict=True):
                for i, t in ((a, ta), (b, tb)):
                    if i not in memo:
                        if len(memo) > 2000:
                            memo.clear()
                        memo[i] = shingle_hashes([t])[0]
                ok.append(_linked(memo[a] if a in memo else shingle_hashes([ta])[0], memo[b], percent))
            yield df.loc[ok, ["a", "b"]]

    return pairs.mapInPandas(run, "a long, b long")


def search_block(ids: np.ndarray, comps: np.ndarray, sets: list[np.ndarray], side: np.ndarray | None, percent: int = LINK_PERCENT) -> list[tuple[int, int]]:
    """Links that join components of the given classes, one for each join at most.

    Intersections of all sets at once: a shared shingle is a column of an incidence matrix, and
    the matrix times its transpose counts. side: only pairs across the two sides are searched.
    """
    n = len(ids)
    sizes = np.array([len(s) for s in sets])
    owner = np.repeat(np.arange(n), sizes)
    _, col, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = times[col] > 1
    owner, col = owner[shared], col[shared]
    both = np.zeros((n, n), dtype=np.float32)
    order = np.argsort(col, kind="stable")
    owner, col = owner[order], col[order]
    if len(col):
        col = np.cumsum(np.concatenate(([0], (col[1:] != col[:-1]).astype(np.int64))))
        width = 2048
        for lo in range(0, int(col[-1]) + 1, width):
            a, b = np.searchsorted(col, (lo, lo + width))
            m = np.zeros((n, width), dtype=np.float32)
            m[owner[a:b], col[a:b] - lo] = 1
            both += m @ m.T
    i, j = np.nonzero(np.triu(100 * both >= percent * (sizes[:, None] + sizes[None, :] - both), 1))
    keep = comps[i] != comps[j]
    if side is not None:
        keep &= side[i] != side[j]
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            root[x] = x = root[root[x]]
        return x

    out = []
    for p, q in zip(i[keep].tolist(), j[keep].tolist(), strict=True):
        x, y = find(int(comps[p])), find(int(comps[q]))
        if x != y:
            root[x] = y
            out.append((int(ids[p]), int(ids[q])))
    return out


def _by_block(members: DataFrame, judge, schema: str) -> DataFrame:
    """judge(rows of one block) for every block; rows are dealt and sorted by block, and a block is at most 2 * BLOCK rows."""

    @tidy
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        for df in batches:
            if not len(df):
                continue
            block = df["block"].to_numpy()
            cut = [0, *(np.flatnonzero(block[1:] != block[:-1]) + 1).tolist(), len(df)]
            for a, b in zip(cut, cut[1:], strict=False):
                part = df.iloc[a:b]
                if held and held[0]["block"].iloc[0] != part["block"].iloc[0]:
                    yield judge(pd.concat(held).drop_duplicates("id"))
                    held = []
                held.append(part)
        if held:
            yield judge(pd.concat(held).drop_duplicates("id"))

    return members.repartition("block").sortWithinPartitions("block", "id").mapInPandas(run, schema)


def promising(regs: np.ndarray, comps: np.ndarray, side: np.ndarray | None, percent: int = LINK_PERCENT, rows: int = 64) -> np.ndarray:
    """Which rows have a partner in another component (and on the other side) whose estimate allows a link."""
    n, found = len(regs), np.zeros(len(regs), dtype=bool)
    for a in range(0, n, rows):
        near = estimate(regs[a : a + rows, None, :], regs[None, :, :]) >= percent / 100 - ESTIMATE_SLACK
        near &= comps[a : a + rows, None] != comps[None, :]
        if side is not None:
            near &= side[a : a + rows, None] != side[None, :]
        found[a : a + rows] |= near.any(axis=1)
        found |= near.any(axis=0)
    return found


def candidates_in_blocks(members: DataFrame, percent: int = LINK_PERCENT) -> DataFrame:
    """Of the rows (block, side, id, comp, regs) those that may have a link into another component of their block, by the estimates from registers alone; texts are fetched for them only."""

    def judge(df: pd.DataFrame) -> pd.DataFrame:
        comps, side = df["comp"].to_numpy(), df["side"].to_numpy()
        keep = np.zeros(len(df), dtype=bool)
        if not (comps == comps[0]).all():
            keep = promising(np.frombuffer(b"".join(df["regs"]), dtype="<u2").reshape(-1, BUCKETS), comps, side if side.max() else None, percent)
        return df.loc[keep, ["block", "side", "id", "comp"]]

    return _by_block(members, judge, "block long, side int, id long, comp long")


def joining_links(members: DataFrame, percent: int = LINK_PERCENT) -> DataFrame:
    """Links between different components inside the blocks, of rows (block, side, id, comp, text)."""

    def judge(df: pd.DataFrame) -> pd.DataFrame:
        comps, side, out = df["comp"].to_numpy(), df["side"].to_numpy(), []
        if not (comps == comps[0]).all():
            texts = df["text"].tolist()
            sets = [s for part in text_batches(texts) for s in shingle_hashes(texts[part])]
            out = search_block(df["id"].to_numpy(), comps, sets, side if side.max() else None, percent)
        return pd.DataFrame(out, columns=["a", "b"], dtype=np.int64)

    return _by_block(members, judge, "a long, b long")


def components(links: DataFrame, path: str) -> DataFrame:
    """(id, comp) for every id in a link: comp is the smallest id reachable.

    Each round every id points at the smallest label around it and then at that label's own
    label, so paths shorten by doubling; rounds are written to the shared folder.
    """
    spark = links.sparkSession
    both = keep(links.select("a", "b").union(links.select("b", "a")).distinct(), f"{path}/edges")
    label = keep(both.groupBy("a").agg(F.least("a", F.min("b")).alias("comp")).withColumnRenamed("a", "id"), f"{path}/label0")
    turn = 0
    while True:
        turn += 1
        near = both.join(label, both["b"] == label["id"]).groupBy("a").agg(F.min("comp").alias("near"))
        hooked = label.join(near, label["id"] == near["a"]).select("id", "comp", F.least("comp", "near").alias("new"))
        # the old label's owner learns of the smaller label as well
        told = hooked.where("new < comp").groupBy(F.col("comp").alias("id")).agg(F.min("new").alias("told"))
        low = hooked.join(told, "id", "left").select("id", F.col("comp").alias("old"), F.least("new", F.coalesce("told", "new")).alias("comp"))
        low = keep(low, f"{path}/low{turn}")
        jump = low.select(F.col("id").alias("comp"), F.col("comp").alias("further"))
        label_next = keep(low.join(jump, "comp", "left").select("id", "old", F.least("comp", F.coalesce("further", "comp")).alias("comp")), f"{path}/label{turn}")
        changed = label_next.where("old <> comp").limit(1).count()
        drop(spark, f"{path}/low{turn}", *([f"{path}/label{turn - 1}"] if turn else []))
        label = label_next.select("id", "comp")
        if not changed:
            return label


def group(docs: DataFrame, *, percent: int = LINK_PERCENT, folder: str | None = None) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for every row of docs (columns doc_id and text; others are ignored). percent: the Jaccard similarity of a link; bands are made for 80 and more.

    A null or wordless text has an empty set and is linked with nothing. Rows that repeat a
    doc_id are each returned; they count as one document, linked with whatever any of them is
    linked with. A row without doc_id belongs to the class of its text, null if no row of the
    class has an id, and is never kept. An empty table gives an empty result.
    """
    spark = docs.sparkSession
    path = folder or workspace(spark, "neardup")
    prof = keep(profiles(docs), f"{path}/profiles")
    # one class for each set; its id is the smallest doc_id, and links between classes that share an id come from repeated ids
    classes = keep(prof.where("fp is not null and doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("id"), F.first("regs").alias("regs")), f"{path}/classes")
    repeats = prof.where("fp is not null and doc_id is not null").select("doc_id", "fp").distinct().groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1")
    same_id = prof.join(repeats, "doc_id").join(classes.select("fp", "id"), "fp").where("id <> doc_id").select(F.col("doc_id").alias("a"), F.col("id").alias("b")).distinct()
    bands = keep(bands_of(classes), f"{path}/bands")
    per_key = bands.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    crowded = keep(bands.join(per_key, "key"), f"{path}/crowded")  # buckets of two and more
    drop(spark, f"{path}/bands")
    # a class that meets many others is a good centre: the original of a family of edited copies shares most buckets with them
    weight = crowded.groupBy("id").agg(F.sum("n").alias("w"))
    weighed = crowded.join(weight, "id")
    hubs = weighed.groupBy("key").agg(F.max_by("id", F.struct("w", -F.col("id"))).alias("hub"))
    spokes = crowded.select("key", "id").join(hubs, "key").where("id <> hub").select(F.least("id", "hub").alias("a"), F.greatest("id", "hub").alias("b")).distinct()
    # texts of the classes that stand in a bucket with others, once each
    seen = docs.select("doc_id", "text").where("text is not null").join(weight.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
    texts = seen.groupBy("doc_id").agg(F.min("text").alias("text")).withColumnRenamed("doc_id", "id")
    texts = keep(texts.join(classes.groupBy("id").agg(F.first("regs").alias("regs")), "id"), f"{path}/texts")
    sides = [texts.select(F.col("id").alias(s), F.col("regs").alias(f"regs_{s}"), F.col("text").alias(f"text_{s}")) for s in "ab"]
    links = keep(confirm(spokes.join(sides[0], "a").join(sides[1], "b")), f"{path}/links1").unionByName(same_id)
    links = keep(links, f"{path}/links")
    comp = components(links, f"{path}/comp1")
    release(spark)
    # buckets that hold more than one component: equal buckets of several bands are searched once
    placed = crowded.select("key", "id").join(comp, "id", "left").select("key", "id", F.coalesce("comp", "id").alias("comp"))
    mixed = placed.groupBy("key").agg(F.count("*").alias("n"), F.min("comp").alias("c0"), F.max("comp").alias("c1"), F.sum(F.xxhash64("id").bitwiseAND(F.lit((1 << 40) - 1))).alias("h1"), F.bit_xor(F.xxhash64("id", F.lit(1))).alias("h2")).where("c0 <> c1")
    mixed = mixed.groupBy("n", "h1", "h2").agg(F.min("key").alias("key"))
    blocks = placed.join(mixed.select("key", "n"), "key").select("key", "id", "comp", F.ceil(F.col("n") / BLOCK).cast("int").alias("parts"))
    blocks = blocks.withColumn("part", F.pmod(F.xxhash64("id", F.lit(2)), F.col("parts")).cast("int"))
    # every two parts of a bucket meet in one block; a part with itself too
    blocks = blocks.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    blocks = blocks.select(F.xxhash64("key", F.least("part", "other"), F.greatest("part", "other")).alias("block"), F.when(F.col("part") < F.col("other"), 1).when(F.col("part") > F.col("other"), 2).otherwise(0).alias("side"), "id", "comp")
    rated = keep(candidates_in_blocks(blocks.join(texts.select("id", "regs"), "id"), percent), f"{path}/rated")
    more = keep(joining_links(rated.join(texts.select("id", "text"), "id"), percent), f"{path}/links2")
    drop(spark, f"{path}/crowded", f"{path}/texts", f"{path}/rated")
    release(spark)
    final = components(links.unionByName(more), f"{path}/comp2")
    of_class = keep(classes.select("fp", "id").join(final, "id", "left").select("fp", F.coalesce("comp", "id").alias("component")), f"{path}/of_class")
    # the classes' hot fingerprints sit on the larger side only, where a skewed join is split
    out = prof.select("doc_id", "n_shingles", "fp").join(of_class, "fp", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"), F.coalesce(F.coalesce("component", "doc_id") == F.col("doc_id"), F.lit(False)).alias("kept"))


def keep_one_of_each(docs: DataFrame, *, percent: int = LINK_PERCENT) -> DataFrame:
    """The document with the smallest doc_id of each group, once; documents without an id stay as they are. Any other columns pass through."""
    kept = group(docs, percent=percent).where("kept").select("doc_id").distinct()
    rest = docs.where("doc_id is null")
    w = Window.partitionBy("doc_id").orderBy(F.xxhash64(*[F.col(f"`{c}`") for c in docs.columns]))
    copy = fresh(docs, "__copy")
    first = docs.join(kept, "doc_id", "left_semi").withColumn(copy, F.row_number().over(w)).where(F.col(copy) == 1).drop(copy)
    return first.unionByName(rest)


def op1(spark, sf_dir: str) -> DataFrame:
    return group(table(spark, sf_dir, "documents").select("doc_id", "text"), percent=LINK_PERCENT)
