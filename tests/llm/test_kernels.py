"""Parts of the operators that need no session."""

import random
import zlib

import numpy as np
import pytest

from llm import decontamination as D
from llm import html_text as H
from llm import language_id as L
from llm import near_duplicates as N
from llm import packing as P
from llm import quality, sharding, toxicity
from llm import suffix_dedup as X
from llm.textkit import PrefixHash, shingle_hashes


def slow_shingles(text):
    import re

    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", low)
    return {tuple(words[i : i + 5]) for i in range(len(words) - 4)} if len(words) >= 5 else ({tuple(words)} if words else set())


def test_shingle_sets_match_plain_ones():
    rng = random.Random(1)
    texts = ["", None, " \t\n", "One", "one", "a b c d", "A  b\tC d e", "É é x y z É é"] + [" ".join(rng.choice("aAbBcd é") for _ in range(rng.randrange(30))) for _ in range(60)]
    fast, slow = shingle_hashes(texts), [slow_shingles(t) for t in texts]
    for i in range(len(texts)):
        assert len(fast[i]) == len(slow[i])
        for j in range(i):
            assert len(np.intersect1d(fast[i], fast[j])) == len(slow[i] & slow[j])


def test_hyperminhash_estimates():
    rng = np.random.default_rng(0)
    for share in (0.5, 0.85, 1.0):
        pool = rng.integers(0, 2**64, 4000, dtype=np.uint64)
        k = int(2000 * 2 * share / (1 + share))
        a, b = np.sort(pool[:2000]), np.sort(np.concatenate([pool[:k], pool[2000 : 4000 - k]]))
        r = N.registers([a, b])
        assert N.estimate(r[0], r[1]) == pytest.approx(share, abs=0.16)
    same = N.registers([np.sort(pool[:3]), np.sort(pool[:3])])
    assert (N.band_keys(same)[0] == N.band_keys(same)[1]).all()


def test_search_block_finds_every_join():
    sets = [np.array(s, dtype=np.uint64) for s in (range(20), range(1, 21), range(2, 22), range(100, 110))]
    links = N.search_block(np.arange(4), np.arange(4), sets, None)
    assert sorted(map(sorted, links)) == [[0, 1], [1, 2]] or len(links) == 2
    assert N.search_block(np.arange(4), np.array([0, 0, 0, 3]), sets, None) == []


def brute_repeats(raws, length):
    from collections import Counter

    seen = Counter(r[i : i + length] for r in raws for i in range(len(r) - length + 1))
    out = []
    for r in raws:
        cover = [False] * len(r)
        for i in range(len(r) - length + 1):
            if seen[r[i : i + length]] > 1:
                cover[i : i + length] = [True] * length
        out.append(cover)
    return out


def test_anchors_depend_on_content_only():
    rng = np.random.default_rng(2)
    run = rng.integers(97, 101, 30).astype(np.uint8)
    a, b = (np.concatenate([rng.integers(97, 123, n).astype(np.uint8), run, rng.integers(97, 123, 25).astype(np.uint8)]) for n in (20, 33))
    at = []
    for doc, shift in ((a, 20), (b, 33)):
        place, h, *_ = X.anchors(doc, np.array([0, len(doc)]), length=30, gram=10)
        at.append({(int(p) - shift, int(x)) for p, x in zip(place, h, strict=True)})
    assert {x for x in at[0] & at[1] if 0 <= x[0] <= 20}


def test_suffix_order_and_repeats_match_brute_force():
    rng = random.Random(3)
    for _ in range(20):
        around = ["".join(rng.choice("ab") for _ in range(rng.randrange(6, 14))).encode() for _ in range(rng.randrange(2, 12))]
        n, reach = len(around), np.array([rng.randrange(0, 4) for _ in around])
        base = np.cumsum([0, *map(len, around)])[:-1]
        buf = np.frombuffer(b"".join(around), dtype=np.uint8)
        s = X.Suffixes(buf, base, base + reach, base + np.array(list(map(len, around))))
        order = s.order(np.zeros(n, dtype=np.int64)).tolist()
        tails = [around[i][reach[i] :] for i in order]
        assert tails == sorted(tails)
        marks = X.repeated_starts(np.zeros(n, dtype=np.int64), around, reach, length=6, gram=3)
        for i in range(n):
            for j in range(4):
                mine = around[i][reach[i] - j : reach[i] - j + 6] if reach[i] >= j else b""
                others = [around[k][reach[k] - j : reach[k] - j + 6] for k in range(n) if k != i and reach[k] >= j]
                assert marks[i, j] == (len(mine) == 6 and mine in others)


def test_prefix_hash_rows():
    buf = np.frombuffer(b"abcabcabc", dtype=np.uint8)
    rows = PrefixHash(buf, np.array([0, 3, 6]))
    assert rows.raw(np.array([0]), np.array([3])) == rows.raw(np.array([6]), np.array([9])) == PrefixHash(buf).raw(np.array([3]), np.array([6]))


def test_bit_parallel_distance_matches_the_table():
    rng = random.Random(4)
    for _ in range(200):
        p, t = ("".join(rng.choice("abc") for _ in range(rng.randrange(1, n))) for n in (12, 30))
        masks = {}
        for i, c in enumerate(p):
            masks[c] = masks.get(c, 0) | 1 << i
        prev, best = list(range(len(p) + 1)), None
        for at, c in enumerate(t, 1):
            cur = [0]
            for i, x in enumerate(p, 1):
                cur.append(min(prev[i] + 1, cur[-1] + 1, prev[i - 1] + (x != c)))
            prev = cur
            if best is None or cur[-1] < best[0]:
                best = (cur[-1], at)
        got = D.best_match(masks, len(p), t, len(p))
        assert got == best


def test_leaks_are_found_and_clean_texts_left_alone():
    item = "the quick brown fox jumps over the lazy dog while seven grey wolves watch from the far hill"
    index = D.ItemIndex([(7, item), (8, "too short"), (9, None)])
    assert index.find(f"Intro. {item.upper()}! More.")[0][:2] == (7, 0)
    near = item.replace("lazy", "lary").replace("grey", "gray")
    (found,) = index.find("x y z " + near + " and so on")
    assert found[:2] == (7, 2) and ("x y z " + near + " and so on")[found[2] : found[3]] == near
    assert index.find("a text about something else entirely " * 20) == [] and index.find("") == []


def test_main_text():
    page = "<html><head><title>T</title><style>p{}</style></head><body><nav><a href=x>Home</a></nav><header>Top</header><div class='ad'>Buy</div><article><h1>Head &amp; more</h1><p>One <b>bold\n text</b>.<br>Next<p>Two &lt;x&gt;<script>var t='</p>'</script></p></article><section id='comments'><p>First!</p></section><footer>&copy;</footer></body></html>"
    assert H.extract(page) == "Head & more\nOne bold text . Next\nTwo <x>".replace("text .", "text.")
    assert H.extract(None) == H.extract("") == H.extract("<nav>a</nav>") == ""
    plain = "<body><div><a href=1>a</a> <a href=2>b</a> <a href=3>c</a></div><div><p>" + "A long sentence of the story. " * 8 + "</p><p>" + "And another one that goes on. " * 8 + "</p></div><div><a href=4>d</a> <a href=5>e</a></div></body>"
    got = H.extract(plain)
    assert got.startswith("A long") and "d" not in got.split("\n")


def test_teaser_articles_do_not_displace_the_story():
    story = ["Head", *["A long sentence of the story, told plainly. " * 6] * 4, "Short."]
    body = f"<h1>{story[0]}</h1>" + "".join(f"<p>{x}</p>" for x in story[1:])
    cards = "".join(f"<article><h2><a href={i}>Card {i}</a></h2><p>See what comes next</p></article>" for i in range(4))
    want = "\n".join(x.strip() for x in story)
    for page in (f"{cards}<div>{body}</div>{cards}", f"<main>{cards}<div>{body}</div></main>", f"<div>{body}</div>", f"<article>{body}<ul><li><a href=1>More</a><li><a href=2>Yet more</a></ul></article>"):
        assert H.extract(f"<body>{page}<footer>The end</footer></body>") == want


def test_language_net_learns():
    rng = random.Random(5)
    kinds = {"aa": "the and of in to", "bb": "der die und das ist", "cc": "que los para una del"}
    make = lambda k: " ".join(rng.choice(kinds[k].split()) + rng.choice(["", "s", "n"]) for _ in range(rng.randrange(4, 60)))
    data = [(make(k), k) for k in kinds for _ in range(60)]
    net = L.train([t for t, _ in data], [k for _, k in data], steps=150)
    test = [(make(k), k) for k in kinds for _ in range(20)]
    lang, score = L.predict(net, [t for t, _ in test] + ["", None, "12 34"])
    assert sum(a == k for a, (_, k) in zip(lang, test, strict=False)) >= 57
    assert lang[-3:] == ["und"] * 3 and (score[-3:] == 0).all() and (score <= 1).all()


def test_convolution_by_table_equals_sliding():
    net = L.train(["abc abc", "xyz xyz"] * 4, ["a", "x"] * 4, steps=5)
    x = L.SYMBOL[np.frombuffer(b"Hello, World".ljust(L.WINDOW, b"\0"), dtype=np.uint8)]
    for w, t in net.tables().items():
        slide = sum(net.filters[w][j][x[j : len(x) - w + 1 + j]] for j in range(w)).max(axis=0)
        assert np.allclose(t[np.unique(L.codes(x, w))].max(axis=0), slide, atol=1e-5)


def test_quality_learns_shape():
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcdefg") for _ in range(rng.randrange(2, 7)))
    good = [" ".join(word() for _ in range(30)) for _ in range(80)]
    bad = [" ".join(word().upper() + "!!" for _ in range(30)) for _ in range(80)]
    m = quality.train(good[:60] + bad[:60], [1] * 60 + [0] * 60)
    s = m.score([*good[60:], *bad[60:], "", None])
    assert (s[:20] > 0.5).all() and (s[20:40] < 0.5).all() and np.isfinite(s).all()
    assert quality.train(["x"], [1]).score(["y"])[0] > 0.5


def test_levenshtein_trie_matches_plain_distance():
    lex = toxicity.Lexicon(["stupid", "worthless", "scum"], ["lowei"])
    trie = toxicity.FuzzyTrie(lex)

    def distance(a, b):
        prev = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            cur = [i]
            for j, y in enumerate(b, 1):
                cur.append(min(prev[j] + 1, cur[-1] + 1, prev[j - 1] + (x != y)))
            prev = cur
        return prev[-1]

    rng = random.Random(7)
    words = ["stupid", "stupd", "stuppid", "stxpid", "st", "scum", "scom", "worthles", "wrthlss", "loweischaft", "lowe", "other"]
    words += ["".join(rng.choice("stupidx") for _ in range(rng.randrange(4, 8))) for _ in range(300)]
    for w in words:
        fits = [d for t in lex.words if (d := distance(w, t)) <= toxicity.allowed_edits(t)]
        assert trie.edits(w) == (0 if w.startswith("lowei") else min(fits, default=None)), w


@pytest.mark.parametrize(("stem", "ends"), [("achl", "ichst ichheit icher ichber ichkeit ichung"), ("bome", "ntera ntemi nteta ntega ntedo nteja"), ("réeu", "xpa xment xvi xaux xelle xtion")])
def test_misspelled_members_of_a_stem_are_toxic(stem, ends):
    """In words of German, Spanish and French shape; a word of clean documents is no misspelling."""
    rng = random.Random(9)
    near = "z" + (stem + ends.split()[0])[1:]
    plain = [*("".join(rng.choice("abdnort") for _ in range(6)) for _ in range(300)), near]
    text = lambda *words: " ".join(x for w in words for x in (*rng.choices(plain, k=5), w)) + " " + rng.choice(plain)
    forms = [stem + e for e in ends.split()]
    bad, good = [text(*rng.sample(forms, 3)) for _ in range(120)], [text(rng.choice(plain), near, rng.choice(plain)) for _ in range(240)]
    model = toxicity.train([x for i in range(120) for x in (bad[i], good[2 * i], good[2 * i + 1])], [1, 0, 0] * 120)
    assert any(forms[0].startswith(s) for s in model.lexicon.stems)
    scan = toxicity.Scanner(model.lexicon)
    for f in forms:
        for wrong in (f[:2] + "q" + f[3:], f[:2] + f[3:], f[:3] + "q" + f[3:]):
            assert [h[3] for h in scan.hits(wrong)] == [1], wrong
            assert model.score([text(wrong, wrong, wrong)])[0] >= toxicity.THRESHOLD
    assert scan.hits(near) == [] and model.score([text(near, near, near)])[0] < toxicity.THRESHOLD


def test_quotation_is_told_from_abuse():
    scan = toxicity.Scanner(toxicity.Lexicon(["idiot"], []))
    assert [h[4] for h in scan.hits('He said "you idiot" to them')] == [True]
    assert [h[4] for h in scan.hits("you are an idiot and that is it")] == [False]


def test_packing_plan_places_everything_once():
    rng = random.Random(8)
    for n in (0, 1, 30, 3000):
        hist = {}
        for _ in range(n):
            k = rng.choice([rng.randrange(1, 64), rng.randrange(1, 20)])
            hist[k] = hist.get(k, 0) + 1
        p = P.plan(hist, capacity=64, unit=4)
        length = np.repeat(np.array(list(hist), dtype=np.int64), list(hist.values())) if hist else np.zeros(0, np.int64)
        rank = np.concatenate([np.arange(c) for c in hist.values()]) if hist else np.zeros(0, np.int64)
        seq, slot = P.place(p, length, rank)
        load = np.bincount(seq, weights=length, minlength=1) if n else np.zeros(1)
        assert load.max() <= 64 and len({*zip(seq.tolist(), slot.tolist(), strict=True)}) == n
        assert p.lower_bound <= p.sequences <= p.lower_bound * 1.1 + 2
        assert len(set(seq.tolist())) == p.sequences
    with pytest.raises(ValueError):
        P.plan({65: 1}, capacity=64)


def test_word_tokenizer_equals_the_library():
    tok = P.tokenizer(P.default_tokenizer_file())
    texts = ["Plain words, and 12 numbers!", "a_b__c d'll 's ''", "É ñ ß º µ ÿ", "naïve İstanbul ΣΑΣ 漢字", "x<|endoftext|>y", "", " \n", "½ ² \x85 \xa0 ź", "THE the The"]
    for t in texts * 2:
        assert tok.encode([t])[0] == tok._pack(tok.library.encode(t, add_special_tokens=False).ids), t


def test_word_tokenizer_remembers_what_it_meets_often(monkeypatch):
    """A full cache forgets what was not met lately, not all; results stay those of the library."""
    monkeypatch.setattr(P, "CACHE_CHUNKS", 50)
    tok, learned = P.WordTokenizer(P.default_tokenizer_file()), []
    learn = tok._learn
    monkeypatch.setattr(tok, "_learn", lambda chunks: (learned.extend(chunks), learn(chunks)))
    rng = random.Random(3)
    letters = "abcdefghijklmnopqrstuvwxyzßàéîöøúýþÿÀÉŽſıª'_-.,!12"
    for _ in range(40):
        text = "The naïve often-met straße " + " ".join("".join(rng.choice(letters) for _ in range(rng.randrange(1, 9))) for _ in range(30))
        assert tok.encode([text])[0] == tok._pack(tok.library.encode(text, add_special_tokens=False).ids), text
    for common in ("the", "naïve", "often-met", "straße"):
        assert learned.count(common) == 1


def test_merge_planning():
    s = [sharding.Shard(f"p{i}", 1, b, 0) for i, b in enumerate([10] * 9 + [100] * 2 + [600])]
    groups = sharding.plan_merges(s, target=1000, fan_in=4)
    assert all(sum(x.bytes for x in g) <= 1000 for g in groups) and groups
    assert not any(x.bytes == 600 for g in groups for x in g)
    assert sharding.plan_merges(s[:3], target=1000, fan_in=4) == []
    assert len(sharding.plan_merges(s[:3], target=1000, fan_in=4, final=True)[0]) == 3
    assert zlib.crc32(b"") == 0


def test_letters_and_unlearned_nets():
    net = L.train(["hello there"] * 3, ["en"] * 3, steps=5)
    assert L.predict(net, ["12 ½ Ⅷ ①", None, "", "a"])[0] == ["und", "und", "und", "en"]
    none = L.train([], [])
    lang, score = L.predict(none, ["hello", None])
    assert lang == ["und", "und"] and score.tolist() == [0.0, 0.0]


def test_short_items_stand_between_word_borders():
    index = D.ItemIndex([(1, "Red Fox"), (2, "a benchmark item that is long enough for edits")])
    assert [(i, e, a, b) for i, e, a, b in index.find("the red  fox ran")] == [(1, 0, 4, 12)]
    assert index.find("the redder foxes ran") == [] == index.find("coloured foxy")


def test_places_after_a_dotted_capital_i():
    text = "İİ before. A benchmark item that is long enough for edits! after"
    ((_, edits, a, b),) = D.ItemIndex([(2, "a benchmark item that is long enough for edits")]).find(text)
    assert edits == 0 and text[a:b] == "A benchmark item that is long enough for edits"
    assert toxicity.lowered("İSTUPID") == "istupid"


def test_configuration_program_meets_its_bound():
    """Against an exact optimum: halves and thirds of a sequence fill it without waste; other classes pair up."""
    units = 12
    counts = np.zeros(units + 1, dtype=np.int64)
    counts[[6, 4, 3]] = 20, 30, 40
    solution, bound = P.configurations(counts, units)
    assert np.allclose(sum(t * a for a, t in solution), counts) and all(a @ np.arange(units + 1) <= units for a, _ in solution)
    assert sum(t for _, t in solution) == pytest.approx(30) and bound == pytest.approx(30)
    counts[:] = 0
    counts[[7, 5]] = 10, 4
    solution, bound = P.configurations(counts, units)
    assert bound <= sum(t for _, t in solution) + 1e-9 and sum(t for _, t in solution) == pytest.approx(10, rel=0.05)


def test_ngrams_stay_in_words():
    f, at = quality.features(["ab cd", "ab  cd", "", None])
    assert at[2] - at[1] >= at[1] - at[0] > 0 and at[4] == at[2]
    words = set(quality.features(["abc xyz"])[0].tolist())
    assert set(quality.features(["abc"])[0].tolist()) & words and not set(quality.features(["bcxy"])[0].tolist()) & words


def test_registers_keep_every_row_with_a_partner():
    rng = np.random.default_rng(3)
    base = np.sort(rng.integers(0, 2**64, 300, dtype=np.uint64))
    near = np.sort(np.concatenate([base[:290], rng.integers(0, 2**64, 10, dtype=np.uint64)]))
    far = np.sort(rng.integers(0, 2**64, 300, dtype=np.uint64))
    regs = N.registers([base, near, far])
    assert N.promising(regs, np.array([0, 1, 2]), None).tolist() == [True, True, False]
    assert not N.promising(regs, np.array([0, 0, 2]), None).any()
    assert not N.promising(regs, np.array([0, 1, 2]), np.array([1, 1, 2])).any()
