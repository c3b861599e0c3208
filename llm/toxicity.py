"""Toxicity by a learned lexicon whose misspellings are matched too.

The lexicon is learned from labelled documents: words, and beginnings of words, that occur in
toxic documents and hardly elsewhere. It stands in a trie. A word is read by the trie and a
Levenshtein automaton in step; the pairs of states form one deterministic automaton that is built
as far as words need it. Each hit is weighed by its context: within quotation marks or after a
verb of saying it counts as quotation. A logistic layer over the counts gives the score.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from llm.quality import score as score_with
from llm.store import holdout

THRESHOLD = 0.7
MAX_TRAIN_DOCS = 6000
#: Words of context on either side of a hit.
CONTEXT = 6
#: States the automaton of one Python worker keeps; beyond that it starts anew.
MAX_STATES = 200_000

_token = re.compile(r"[^\W_]+(?:[*@$!1|][^\W_]+)*")
# Verbs of saying in the languages of the tables, and quotation marks.
SAYING = frozenset("said says saying called calls calling wrote writes quoted quote quotes quoting told tells claimed sagte sagt nannte schrieb zitierte dit disait appelé écrit cité dijo dice llamó escribió citó".split())
QUOTES = frozenset("\"“”„«»‹›‘’")


def lowered(text: str) -> str:
    """Lower case, character by character where a letter's lower case is longer than it (as of the dotted capital I), so that places stay."""
    low = text.lower()
    return low if len(low) == len(text) else "".join(x if len(x := c.lower()) == 1 else x[0] for c in text)


@dataclass
class Lexicon:
    """words: whole words, those of the stems' families too; stems: beginnings of words; clean: words near a term that are words of clean documents, and so no misspellings."""

    words: list[str]
    stems: list[str]
    clean: frozenset[str] = frozenset()


def _surprise(bad: int, n_bad: int, good: int, n_good: int) -> float:
    """Log-likelihood ratio of a term's being as frequent in both classes."""
    out, rate = 0.0, (bad + good) / (n_bad + n_good)
    for k, n in ((bad, n_bad), (good, n_good)):
        if k:
            out += k * np.log(k / (n * rate))
        if n - k > 0:
            out += (n - k) * np.log((n - k) / (n * (1 - rate))) if rate < 1 else 0.0
    return 2 * out


def learn_lexicon(texts: list[str], labels: list[int], *, share: float = 0.01, purity: float = 0.97, surprise: float = 20.0, stem_surprise: float = 40.0, stem_lengths: range = range(4, 9)) -> Lexicon:
    """Words and stems that occur in toxic documents and hardly elsewhere.

    A term must be in a share of the toxic documents, pure (the classes weighed equally), far from
    chance, and met between different neighbours about as often as it is met at all: a term that
    only copies of one text hold says nothing about toxicity. A stem needs three different words;
    of stems that begin alike the shortest stays. Words with a stem are hits by it; those of them
    that are pure are terms as well, so that their misspellings are matched inside the stem too.
    """
    seen, n = (Counter(), Counter()), [0, 0]
    tokens = [_token.findall(lowered(t)) for t in texts]
    for words, y in zip(tokens, labels, strict=True):
        n[y] += 1
        seen[y].update(set(words))
    if not n[0] or not n[1]:
        return Lexicon([], [])
    stems, forms = (Counter(), Counter()), Counter()
    for y in (0, 1):
        for w, c in seen[y].items():
            for k in stem_lengths:
                if len(w) > k:
                    stems[y][w[:k]] += c
                    forms[w[:k]] += y
    least = max(6, share * n[1])

    def pure(bad: int, good: int) -> bool:
        return bad / n[1] >= purity * (bad / n[1] + (good + 0.05) / n[0])

    def fit(bad: int, good: int, surprise: float = surprise) -> bool:
        bad, good = min(bad, n[1]), min(good, n[0])
        return bad >= least and pure(bad, good) and _surprise(bad, n[1], good, n[0]) >= surprise

    words = {w for w, c in seen[1].items() if len(w) >= 3 and fit(c, seen[0][w])}
    stem_set = {s for s, c in stems[1].items() if forms[s] >= 3 and fit(c, stems[0][s], stem_surprise)}
    terms = {w: t for w in seen[1] if (t := ({w} & words) | {w[:k] + "…" for k in stem_lengths if len(w) > k and w[:k] in stem_set})}
    around: dict[str, set] = {}
    for doc, y in zip(tokens, labels, strict=True):
        if y:
            for i, w in enumerate(doc):
                for term in terms.get(w, ()):
                    around.setdefault(term, set()).add((doc[i - 1] if i else "", doc[i + 1] if i + 1 < len(doc) else ""))
    words = {w for w in words if 2 * len(around[w]) >= min(seen[1][w], 2 * least)}
    most = Counter()  # of a stem's words the one in the most documents
    for w, t in terms.items():
        for s in t:
            most[s] = max(most[s], seen[1][w])
    stem_set = {s for s in stem_set if 2 * len(around[s + "…"]) >= min(stems[1][s], 2 * least) and 2 * most[s + "…"] <= stems[1][s]}
    stem_set = {s for s in stem_set if not any(s[:j] in stem_set for j in stem_lengths if j < len(s))}
    family = {w for w, c in seen[1].items() if any(w[:j] in stem_set for j in stem_lengths if j < len(w))}
    family = {w for w in family if allowed_edits(w) and pure(seen[1][w], seen[0][w])}
    out = Lexicon(sorted({w for w in words if not any(w[:j] in stem_set for j in stem_lengths)} | family), sorted(stem_set))
    trie = FuzzyTrie(out)
    out.clean = frozenset(w for w, c in seen[0].items() if c / n[0] >= seen[1][w] / n[1] and trie.edits(w))
    return out


def allowed_edits(term: str) -> int:
    """Short terms are too near to other words to be matched with edits."""
    return 0 if len(term) < 5 else 1 if len(term) < 10 else 2


@dataclass
class FuzzyTrie:
    """The trie of a lexicon, walked by Levenshtein automata.

    A state is a set of (node, edits) pairs, closed under skipped letters of the term. States are
    numbered when first met; step[state] maps a character to the next. State 0 accepts nothing.
    """

    lexicon: Lexicon
    children: list[dict[str, int]] = field(default_factory=lambda: [{}])
    ends: dict[int, tuple[bool, int]] = field(default_factory=dict)  # node: (is a stem, edits allowed)
    reach: list[int] = field(default_factory=lambda: [0])  # most edits of any term below a node

    def __post_init__(self):
        for term, stem in [*((w, False) for w in self.lexicon.words), *((s, True) for s in self.lexicon.stems)]:
            node, edits = 0, 0 if stem else allowed_edits(term)
            self.reach[0] = max(self.reach[0], edits)
            for ch in term:
                if ch not in self.children[node]:
                    self.children[node][ch] = len(self.children)
                    self.children.append({})
                    self.reach.append(0)
                node = self.children[node][ch]
                self.reach[node] = max(self.reach[node], edits)
            self.ends[node] = (stem, edits)
        self.reset()

    def reset(self):
        self.numbers: dict[frozenset, int] = {frozenset(): 0}
        self.sets, self.step, self.accept, self.sure = [frozenset()], [{}], [None], [None]
        self.start = self._number({(0, 0)})

    def _close(self, pairs) -> frozenset:
        best: dict[int, int] = {}
        todo = list(pairs)
        while todo:
            node, e = todo.pop()
            if e <= self.reach[node] and e < best.get(node, 99):
                best[node] = e
                todo += [(child, e + 1) for child in self.children[node].values()]  # a letter of the term left out
        return frozenset(best.items())

    def _number(self, pairs) -> int:
        s = self._close(pairs)
        if s not in self.numbers:
            self.numbers[s] = len(self.sets)
            self.sets.append(s)
            self.step.append({})
            hits = [e for node, e in s if node in self.ends and e <= self.ends[node][1]]
            self.accept.append(min(hits, default=None))
            # a stem that has been read whole is a hit whatever follows
            self.sure.append(0 if any(node in self.ends and self.ends[node][0] and e == 0 for node, e in s) else None)
        return self.numbers[s]

    def _next(self, state: int, ch: str) -> int:
        moved = set()
        for node, e in self.sets[state]:
            child = self.children[node].get(ch)
            if child is not None:
                moved.add((child, e))
            moved.add((node, e + 1))  # a letter too many
            moved |= {(c, e + 1) for c in self.children[node].values()}  # a wrong letter
        self.step[state][ch] = out = self._number(moved)
        return out

    def edits(self, word: str) -> int | None:
        """Edits between the word and the nearest term within its allowance; None if there is none. Words with a stem are 0 edits away."""
        if len(self.sets) > MAX_STATES:
            self.reset()
        state, step, sure = self.start, self.step, self.sure
        for ch in word:
            nxt = step[state].get(ch)
            state = self._next(state, ch) if nxt is None else nxt
            if not state:
                return None
            if sure[state] is not None:
                return 0
        return self.accept[state]


#: Counts that the logistic layer reads.
INPUTS = ("exact_direct", "exact_quoted", "fuzzy_direct", "fuzzy_quoted", "density")


class Scanner:
    """Counts of one text's hits by kind; words met before are not walked again."""

    def __init__(self, lexicon: Lexicon):
        self.trie, self.clean, self.known = FuzzyTrie(lexicon), lexicon.clean, {}

    def hits(self, text: str) -> list[tuple[str, int, int, int, bool]]:
        """(word, start, end, edits, quoted) of every hit."""
        low = lowered(text)
        words = _token.findall(low)
        if len(self.known) > MAX_STATES:
            self.known.clear()
        known, hit = self.known, False
        for w in set(words):
            if w not in known:
                known[w] = None if w in self.clean else self.trie.edits(w)
            hit = hit or known[w] is not None
        if not hit:
            return []
        out, spans = [], [(m.group(), m.start(), m.end()) for m in _token.finditer(low)]
        for i, (w, a, b) in enumerate(spans):
            e = self.known[w]
            if e is not None:
                left = spans[max(0, i - CONTEXT)][1]
                right = spans[min(len(spans) - 1, i + CONTEXT)][2]
                marks = any(c in QUOTES for c in text[left:a]) and any(c in QUOTES for c in text[b:right])
                saying = any(x[0] in SAYING for x in spans[max(0, i - 3) : i])
                out.append((w, a, b, e, marks or saying and any(c in QUOTES for c in text[left:right])))
        return out

    def inputs(self, text) -> np.ndarray:
        x = np.zeros(len(INPUTS))
        if isinstance(text, str) and text:
            found = self.hits(text)
            for _, _, _, e, quoted in found:
                x[(2 if e else 0) + quoted] += 1
            if found:
                x[4] = 100 * len(found) / (1 + len(text) / 6)
        return np.minimum(x, 6)  # saturates: the tenth hit says no more than the sixth


@dataclass
class ToxicityModel:
    lexicon: Lexicon
    weight: np.ndarray
    bias: float

    def score(self, texts) -> np.ndarray:
        if getattr(self, "_scanner", None) is None:
            self._scanner = Scanner(self.lexicon)
        z = np.array([self._scanner.inputs(t) for t in texts]).reshape(-1, len(INPUTS)) @ self.weight + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "_scanner"}


def misspell(word: str, rng: np.random.Generator) -> str:
    """The word with a wrong, a missing or an extra letter behind its first one; words too short to be matched with edits as they are."""
    if not allowed_edits(word):
        return word
    i, letter = int(rng.integers(1, min(len(word), 8))), word[int(rng.integers(len(word)))]
    return word[:i] + (letter, "", word[i] + letter)[int(rng.integers(3))] + word[i + 1 :]


def misspelled(text: str, scanner: Scanner, rng: np.random.Generator) -> str:
    """The text with every hit misspelled."""
    out, last = [], 0
    for word, a, b, _, _ in scanner.hits(text):
        out += [text[last:a], misspell(word, rng)]
        last = b
    return "".join([*out, text[last:]])


def train(texts: list[str], labels: list[int], *, steps: int = 800, lr: float = 0.3) -> ToxicityModel:
    """Lexicon from one half of the rows, the logistic layer from the other, so that its weights know how the lexicon fares on new texts; then the lexicon is learned anew from all. Of every row the layer also reads a copy with misspelled hits: few rows have misspellings of their own to learn from. Only one label: a constant model."""
    y = np.array([int(v) for v in labels])
    if len(set(y.tolist())) < 2:
        share = float(y.mean()) if len(y) else 0.5
        return ToxicityModel(Lexicon([], []), np.zeros(len(INPUTS)), float(np.log((share + 0.01) / (1.01 - share))))
    half = np.arange(len(y)) % 2 == 0
    first = learn_lexicon([t for t, h in zip(texts, half, strict=True) if h], y[half].tolist())
    scanner = Scanner(first)
    rng, rest = np.random.default_rng(5), [t for t, h in zip(texts, half, strict=True) if not h]
    x = np.array([scanner.inputs(t) for t in [*rest, *(misspelled(t, scanner, rng) for t in rest)]]).reshape(-1, len(INPUTS))
    t = np.tile(y[~half], 2)
    w, b = np.full(len(INPUTS), 1.0), -2.0
    mass = np.where(t == 1, 0.5 / max(1, t.sum()), 0.5 / max(1, (1 - t).sum()))  # the classes weigh the same
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w + b, -30, 30)))
        d = (p - t) * mass
        w -= lr * 4 * (x.T @ d + 1e-4 * w)
        b -= lr * 4 * d.sum()
    return ToxicityModel(learn_lexicon(texts, y.tolist()), w, b)


def fit(docs: DataFrame, labels: DataFrame, label_col: str, *, condition: str | None = None, max_docs: int = MAX_TRAIN_DOCS) -> ToxicityModel:
    """Learn from at most max_docs labelled documents that meet the SQL condition on doc_id, each whole; half of the places go to toxic ones, as far as there are any. Of rows that share an id the smallest text and the larger label count."""
    known = labels.select("doc_id", F.col(label_col).cast("int").alias("y")).where("y in (0, 1) and doc_id is not null")
    if condition:
        known = known.where(condition)
    known = known.groupBy("doc_id").agg(F.max("y").alias("y"))
    order = (F.xxhash64("doc_id"), "doc_id")
    bad = known.where("y = 1").orderBy(*order).limit(max_docs // 2)
    good = known.where("y = 0").orderBy(*order).limit(max_docs // 2)
    rows = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(bad.unionByName(good)), "doc_id")  # max_docs rows bound the broadcast
    sample = rows.groupBy("doc_id", "y").agg(F.min("text").alias("text")).toPandas().sort_values(["doc_id", "text"])  # a row for each labelled document of the sample
    return train(sample["text"].tolist(), sample["y"].tolist())


def score(docs: DataFrame, model: ToxicityModel, *, text_col: str = "text", out_col: str = "score") -> DataFrame:
    """Every row with the probability that its whole text is toxic; null counts as empty. An old column of that name is replaced."""
    return score_with(docs, model, text_col=text_col, out_col=out_col)


def hit_spans(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """One row for each hit: doc_id, word, start, end (in characters), edits, quoted."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        scanner = Scanner(model.lexicon)
        for df in batches:
            rows = [(d, *h) for d, t in zip(df["doc_id"], df["text"], strict=True) if isinstance(t, str) for h in scanner.hits(t)]
            yield pd.DataFrame(rows, columns=["doc_id", "word", "start", "end", "edits", "quoted"])

    return docs.select("doc_id", "text").where("doc_id is not null").mapInPandas(run, "doc_id long, word string, start int, end int, edits int, quoted boolean")


HELD_OUT = holdout("doc_id", 3, 1)


def op8(spark, sf_dir: str) -> DataFrame:
    from llm.store import table

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels"), "toxic", condition=f"not ({HELD_OUT})")
    return score(docs, model).select("doc_id", F.expr(HELD_OUT).alias("held_out"), "score", F.expr(f"cast(score >= {THRESHOLD} as int)").alias("predicted"))
