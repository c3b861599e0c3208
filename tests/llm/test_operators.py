"""Operators on small tables with awkward rows, against brute force."""

import hashlib

import numpy as np
import pytest

from conftest import SMALL
from llm import decontamination, html_text, language_id, near_duplicates, neighbours, packing, quality, sharding, suffix_dedup, toxicity
from llm.store import workspace
from test_kernels import brute_repeats, slow_shingles

BASE = " ".join(f"word{i}" for i in range(60))
ROWS = [
    (1, BASE, "en", "s", "x"),
    (2, BASE, "en", "s", "x"),
    (3, BASE.replace("word30", "other"), "en", "s", None),
    (4, BASE.upper(), None, None, None),
    (5, None, None, None, None),
    (6, "", "en", "s", None),
    (7, "two words", "en", "s", None),
    (8, "Two Words", "en", "s", None),
    (9, "é" * 700, "fr", "s", None),
    (10, "lone text of its own with five words and more", "en", "s", None),
    (10, "lone text of its own with five words and more", "en", "s", None),
    (11, " ".join(f"w{i % 7}" for i in range(4000)), "en", "s", None),
    (None, BASE, "en", "s", None),
]
SCHEMA = "doc_id long, text string, lang string, source string, fp string"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def brute_components(rows):
    sets = {}
    for i, t, *_ in rows:
        if i is not None:
            sets.setdefault(i, []).append(slow_shingles(t))
    ids = sorted(sets)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and any(s and t and 100 * len(s & t) >= 85 * len(s | t) for s in sets[a] for t in sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: find(i) for i in ids}


def test_near_duplicates(docs, none):
    out = near_duplicates.group(docs).collect()
    want = brute_components(ROWS)
    assert len(out) == len(ROWS)
    for r in out:
        if r["doc_id"] is not None:
            assert r["component_id"] == want[r["doc_id"]] and r["kept"] == (r["doc_id"] == want[r["doc_id"]])
        else:
            assert r["component_id"] == 1 and not r["kept"]
    assert near_duplicates.group(none).count() == 0
    kept = near_duplicates.keep_one_of_each(docs)
    assert kept.columns == docs.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == sorted([0, *set(want.values())])


def test_near_duplicates_of_a_family_in_blocks(spark, monkeypatch):
    """Many edits of one text: links between members that no centre explains are found in small blocks too."""
    monkeypatch.setattr(near_duplicates, "BLOCK", 4)
    rng = np.random.default_rng(1)
    rows = []
    for i in range(40):
        words = [f"w{k}" for k in range(120)]
        for _ in range(rng.integers(0, 5)):
            words[rng.integers(0, 120)] = f"z{rng.integers(0, 4)}"
        rows.append((i, " ".join(words), "", "", ""))
    out = {r["doc_id"]: r["component_id"] for r in near_duplicates.group(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert out == brute_components(rows)


def test_pipeline_links_at_80_percent(spark):
    """Pairs at 0.82 and 0.80 are one document for the pipeline and two for op1; 0.79 is two for both."""
    import corpus_pipeline

    rows, shares = [], []
    for k, words in enumerate((49, 54, 51)):
        text = [f"p{k}w{i}" for i in range(words + 4)]
        other = [*text[:20], f"p{k}other", *text[21:]]
        a, b = slow_shingles(" ".join(text)), slow_shingles(" ".join(other))
        shares.append(len(a & b) / len(a | b))
        rows += [(2 * k, " ".join(text), "", "", ""), (2 * k + 1, " ".join(other), "", "", "")]
    assert [round(x, 2) for x in shares] == [0.81, 0.83, 0.82]
    rows += [(10, " ".join(f"e{i}" for i in range(49)), "", "", ""), (11, " ".join("x" if i == 20 else f"e{i}" for i in range(49)), "", "", "")]  # 40 of 50
    rows += [(12, " ".join(f"f{i}" for i in range(46)), "", "", ""), (13, " ".join("x" if i == 20 else f"f{i}" for i in range(46)), "", "", "")]  # 37 of 47
    docs = spark.createDataFrame(rows, SCHEMA)
    kept = corpus_pipeline.drop_near_duplicates(spark, docs, SMALL)
    assert sorted(r["doc_id"] for r in kept.collect()) == [0, 2, 4, 10, 12, 13]
    assert near_duplicates.group(docs).where("kept").count() == len(rows)


@pytest.mark.parametrize("hot", [50_000, 2])
def test_repeats(docs, none, hot, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    raws = [(t or "").encode() for _, t, *_ in ROWS]
    want = []
    for (i, *_), raw, cover in zip(ROWS, raws, brute_repeats(raws, suffix_dedup.LENGTH), strict=True):
        rest = bytes(b for b, c in zip(raw, cover, strict=True) if not c)
        spans = sum(c and (k == 0 or not cover[k - 1]) for k, c in enumerate(cover))
        want.append((i, len(raw), sum(cover), spans, hashlib.sha256(rest).hexdigest()))
    got = [tuple(r) for r in suffix_dedup.measure(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert suffix_dedup.measure(none).count() == 0
    cut = suffix_dedup.remove_repeats(docs)
    assert cut.columns == docs.columns and cut.count() == len(ROWS)


def test_packing(docs, none, spark):
    out = packing.pack(packing.pieces(docs)).toPandas()
    tok = packing.tokenizer(packing.default_tokenizer_file())
    assert len(out) >= len(ROWS) and out["length"].max() <= packing.CAPACITY
    for _, g in out.groupby("sequence_id"):
        g = g.sort_values("offset")
        assert g["offset"].tolist() == [0, *np.cumsum(g["length"])[:-1].tolist()] and g["length"].sum() <= packing.CAPACITY
    total = sum(len(tok.library.encode(t or "", add_special_tokens=False).ids) + 1 for _, t, *_ in ROWS)
    assert out["length"].sum() == total
    assert packing.pack(packing.pieces(none)).count() == 0


def test_decontamination(docs, none, spark):
    items = spark.createDataFrame([(1, BASE[:180]), (2, None), (3, ""), (3, "no such passage stands in any of the texts of this table")], "item_id long, text string")
    blocks = decontamination.item_blocks(items)
    assert {(r["doc_id"], r["item_id"]) for r in decontamination.matches(docs, blocks).collect()} == {(1, 1), (2, 1), (3, 1), (4, 1), (None, 1)}
    clean = decontamination.clean(docs, blocks)
    assert clean.columns == docs.columns and clean.count() == len(ROWS) - 5
    assert decontamination.matches(none, blocks).count() == 0
    assert decontamination.clean(docs, decontamination.item_blocks(items.limit(0))).count() == len(ROWS)
    many = decontamination.item_blocks(items, block_chars=100)
    assert len(many) > 1 and decontamination.clean(docs, many).count() == len(ROWS) - 5


def test_sharding(docs, none, spark):
    store = sharding.ShardStore(spark, workspace(spark, "test-shards"))
    assert store.manifest().version == 0 and store.read(docs.schema).count() == 0
    for _ in range(3):
        store.append(docs)
    before = store.manifest()
    with pytest.raises(sharding.VersionTaken):
        store.commit(before)
    m = store.compact(docs.schema, final=True)
    assert len(m.shards) < len(before.shards) and sum(s.rows for s in m.shards) == 3 * len(ROWS)
    assert store.read(docs.schema, before.version).count() == 3 * len(ROWS)
    store.vacuum()
    got = store.read(docs.schema).drop("__shard")
    assert got.exceptAll(docs.union(docs).union(docs)).count() == 0 and got.count() == 3 * len(ROWS)
    store.append(none)
    assert store.read(docs.schema).count() == 3 * len(ROWS)


def test_classifiers(docs, none, spark):
    net = language_id.fit(docs)
    out = {r["doc_id"]: r for r in language_id.identify(docs, net).collect()}
    assert out[5]["lang_pred"] == out[6]["lang_pred"] == "und" and out[9]["lang_pred"] == "fr" and 0 <= out[1]["lang_score"] <= 1
    assert language_id.identify(none, net).count() == 0
    labels = spark.createDataFrame([(1, 1, 0), (7, 0, 1), (9, None, None)], "doc_id long, quality int, toxic int")
    for module, col in ((quality, "quality"), (toxicity, "toxic")):
        model = module.fit(docs, labels, col)
        scored = module.score(docs, model)
        assert scored.count() == len(ROWS) and scored.where("score is null or score < 0 or score > 1").count() == 0
        assert module.score(none, model).count() == 0
        module.fit(docs, labels.limit(0), col)


def test_pages(spark):
    pages = spark.createDataFrame([(1, "u", None, "x"), (2, "u", "", "x"), (3, None, "<article><p>a&amp;b</p></article>", None)], "page_id long, url string, html string, text string")
    assert [r["text"] for r in html_text.extract_pages(pages).orderBy("page_id").collect()] == ["", "", "a&b"]


def test_unmarked_copies_give_the_same_text(duck):
    """Ratios and clusters alone, on the given pages with their marks taken away."""
    for (html,) in duck.execute("select html from pages").fetchall():
        assert html_text.extract(html.replace("<article", "<div").replace("</article", "</div")) == html_text.extract(html) != ""


@pytest.mark.parametrize("unit", [True, False])
def test_neighbours_against_brute_force(spark, unit):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(90, 8))
    x[40:60] = x[40]
    if unit:
        x /= np.linalg.norm(x, axis=1, keepdims=True)
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(200, None), (201, [0.0] * 8), (202, [float("nan")] * 8), (203, [1.0, None] * 4), (None, [1.0] * 8), (220, [1.0] * 3)]
    out = neighbours.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).toPandas()
    found = 0
    for q in range(0, 90, 20):
        s = np.array([sum(a * b for a, b in zip(x[q], v, strict=True)) for v in x])
        want = sorted((i for i in range(90) if i != q), key=lambda i: (-s[i], i))[:20]
        got = out[out["query_id"] == q].sort_values("rank")
        assert np.allclose(got["score"], s[got["vec_id"]]) and got["rank"].tolist() == list(range(1, 21))
        assert not unit or got["vec_id"].tolist() == want
        found += len(set(want) & set(got["vec_id"]))
    assert found >= 0.9 * 100
    empty = spark.createDataFrame([(1, None)], "vec_id long, embedding array<double>")
    assert neighbours.nearest(empty).count() == 0


def test_pipeline_stages(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, before, SMALL)
        assert after.columns == docs.columns, name
        path = workspace(spark, name)
        after.write.parquet(path)
        after = spark.read.parquet(path)
        assert 0.8 * before.count() <= after.count() <= before.count(), name
        before = after
    packed = corpus_pipeline.STAGES[-1][1](spark, before, SMALL)
    assert packed.select("doc_id").distinct().count() == before.select("doc_id").distinct().count()


def test_registry():
    from llm import registry

    names = list(registry.queries())
    assert sorted(int(n[2:].split("_")[0]) for n in names) == list(range(1, 11)) and set(registry.oracle_sql()) <= set(names)


def test_two_writers_of_one_version(docs, spark):
    """Both have read the same manifest: one commits, the other fails and applies its change to the newer one."""
    store = sharding.ShardStore(spark, workspace(spark, "two-writers"))
    store.append(docs)
    now = store.manifest()
    store.commit(sharding.Manifest(now.version + 1, now.shards))
    with pytest.raises(sharding.VersionTaken):
        store.commit(sharding.Manifest(now.version + 1, ()))
    assert store.manifest().shards == now.shards
    gone = [list(now.shards)]
    store.merge(gone, docs.schema)
    with pytest.raises(sharding.ShardsGone):
        store.merge(gone, docs.schema)
    assert store.read(docs.schema).count() == len(ROWS)


def test_clashing_columns(docs, spark):
    from pyspark.sql import functions as F

    odd = docs.withColumns({c: F.lit(1) for c in ("k1", "k2", "__spans", "__lid", "__copy", "lang_pred", "lang_score")})
    assert suffix_dedup.remove_repeats(odd).columns == odd.columns
    assert near_duplicates.keep_one_of_each(odd).columns == odd.columns
    net = language_id.fit(docs)
    kept = language_id.filter_stage(odd, net)
    assert kept.columns == odd.columns and kept.where("lang_pred <> 1").count() == 0
    assert language_id.filter_stage(docs, language_id.fit(docs.limit(0))).count() == len(ROWS)
    pieces = packing.pieces(docs).withColumn("offset", F.lit("x"))
    packed = packing.pack(pieces)
    assert dict(packed.dtypes)["offset"] == "bigint" and packed.count() == pieces.count()


def test_descend_and_slices(spark, monkeypatch):
    """Small cells, slices of them and rounds of NN-descent on 3,000 vectors: recall against brute force."""
    for name, value in (("CELL", 100), ("CELL_MAX", 150), ("MAX_PIVOTS", 8)):
        monkeypatch.setattr(neighbours, name, value)
    rng = np.random.default_rng(8)
    centres = rng.normal(size=(30, 16))
    x = centres[rng.integers(0, 30, 3000)] + 0.5 * rng.normal(size=(3000, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    out = neighbours.nearest(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>"), every=100).toPandas()
    found = 0
    for q in range(0, 3000, 100):
        s = x @ x[q]
        s[q] = -np.inf
        found += len(set(np.argsort(-s)[:20].tolist()) & set(out[out["query_id"] == q]["vec_id"]))
    assert found >= 0.9 * 600
