"""Benchmark decontamination: which documents hold a benchmark item, a few edits apart.

An item that stands in a text with at most k edits leaves at least one of any k + 1 pieces of it
unharmed. So all pieces of all items are sought at once with one automaton pass over the text,
and only around piece hits the edit distance is computed, bit-parallel, a machine-independent
word for the whole item.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from llm.textkit import tidy

#: Edits allowed for each character of a normalised item.
ERROR_RATE = 0.08
#: Items shorter than this, normalised, are too near to other texts to be matched with edits: they must stand there as they are, between word borders.
MIN_ITEM_CHARS = 24
#: Characters of benchmark text in one pass over the documents; a larger benchmark takes more passes.
BLOCK_CHARS = 4_000_000

_gap = re.compile(r"[\W_]+")


def normalise(text: str) -> str:
    """Lower case, every run of other characters than letters and digits one space. Gaps are sought before letters are lowered, as in normalised_spans."""
    return _gap.sub(" ", text).strip().lower()


def normalised_spans(text: str) -> tuple[str, list[int]]:
    """The same with the place in the original of each character; slower, for texts with a match."""
    out, at = [], []
    for m in re.finditer(r"[^\W_]+", text):
        if out:
            out.append(" ")
            at.append(m.start() - 1)
        for i in range(m.start(), m.end()):
            low = text[i].lower()
            out.append(low)
            at += [i] * len(low)
    return "".join(out), at


def split_pieces(item: str, budget: int) -> list[tuple[int, str]]:
    """budget + 1 pieces of nearly equal length that cover the item, each with its offset."""
    n = budget + 1
    cuts = [len(item) * j // n for j in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


def best_match(masks: dict[str, int], size: int, text: str, budget: int) -> tuple[int, int] | None:
    """(edits, end) of the best place in text of the pattern behind masks, if within the budget; the first of equals.

    The column of the edit-distance table is kept as two bit vectors of rises and falls.
    """
    full, top = (1 << size) - 1, 1 << (size - 1)
    rise, fall, score = full, 0, size
    found = None
    for at, ch in enumerate(text):
        eq = masks.get(ch, 0)
        v = eq | fall
        h = (((eq & rise) + rise) ^ rise) | eq
        h_rise = fall | (~(h | rise) & full)
        h_fall = rise & h
        if h_rise & top:
            score += 1
        elif h_fall & top:
            score -= 1
        h_rise, h_fall = h_rise << 1, h_fall << 1  # a match may start anywhere: row 0 stays 0
        rise = (h_fall | ~(v | h_rise)) & full
        fall = h_rise & v & full
        if score <= budget and (found is None or score < found[0]):
            found = (score, at + 1)
    return found


class ItemIndex:
    """Pieces of the items of one block in one automaton."""

    def __init__(self, items: list[tuple[int, str]], rate: float = ERROR_RATE, min_chars: int = MIN_ITEM_CHARS):
        import ahocorasick

        self.items = []
        pieces: dict[str, list[tuple[int, int]]] = {}
        for item_id, raw in items:
            text = normalise(raw or "")
            if not text:
                continue
            budget = int(rate * len(text)) if len(text) >= min_chars else -1  # -1: as it is, between word borders
            masks: dict[str, int] = {}
            for i, ch in enumerate(text):
                masks[ch] = masks.get(ch, 0) | 1 << i
            for offset, piece in split_pieces(text, max(0, budget)):
                pieces.setdefault(piece, []).append((len(self.items), offset))
            self.items.append((item_id, text, budget, masks))
        self.automaton = ahocorasick.Automaton()
        for piece, owners in pieces.items():
            self.automaton.add_word(piece, (len(piece), owners))
        if pieces:
            self.automaton.make_automaton()
        self.empty = not pieces

    def find(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item_id, edits, start, end) of the best place of each item in text; start and end count characters of the original."""
        if self.empty or not text:
            return []
        body = normalise(text)
        windows: dict[int, list[int]] = {}
        for end, (size, owners) in self.automaton.iter(body):
            for k, offset in owners:
                windows.setdefault(k, []).append(end + 1 - size - offset)
        out = []
        for k, starts in windows.items():
            item_id, item, budget, masks = self.items[k]
            if budget < 0:
                whole = [s for s in starts if (s == 0 or body[s - 1] == " ") and body[s + len(item) : s + len(item) + 1] in ("", " ")]
                if whole:
                    out.append((item_id, 0, *self._original(text, body, item, 0, min(whole) + len(item))))
                continue
            best, a, b = None, None, None
            for s in sorted(set(starts)):
                if a is not None and s - budget <= b:
                    b = s + len(item) + budget
                    continue
                if a is not None:
                    best = self._better(best, masks, item, body, a, b, budget)
                a, b = max(0, s - budget), s + len(item) + budget
            best = self._better(best, masks, item, body, a, b, budget)
            if best:
                out.append((item_id, best[0], *self._original(text, body, item, *best)))
        return out

    @staticmethod
    def _better(best, masks, item, body, a, b, budget):
        got = best_match(masks, len(item), body[a:b], budget if best is None else best[0] - 1) if best is None or best[0] else None
        return (got[0], a + got[1]) if got else best

    @staticmethod
    def _original(text: str, body: str, item: str, edits: int, end: int) -> tuple[int, int]:
        """The matched passage's place in the original: its end is known, its start is the best over the reversed passage."""
        back = item[::-1]
        masks: dict[str, int] = {}
        for i, ch in enumerate(back):
            masks[ch] = masks.get(ch, 0) | 1 << i
        rows = list(range(len(back) + 1))
        # one column per length of the passage, anchored at its end: plain dynamic programming on numpy rows
        passage = body[max(0, end - len(item) - edits) : end][::-1]
        pattern = np.array([ord(c) for c in back])
        prev, best, best_len = np.array(rows), len(back), 0
        idx = np.arange(len(back) + 1)
        for n, ch in enumerate(passage, 1):
            cost = np.empty_like(prev)
            cost[0] = n
            cost[1:] = np.minimum(prev[1:] + 1, prev[:-1] + (pattern != ord(ch)))
            cost = np.minimum.accumulate(cost - idx) + idx
            if cost[-1] < best:
                best, best_len = int(cost[-1]), n
            prev = cost
        spans = normalised_spans(text)[1]
        return spans[end - best_len], spans[end - 1] + 1


def item_blocks(benchmark: DataFrame, *, id_col: str = "item_id", text_col: str = "text", block_chars: int = BLOCK_CHARS) -> list[list[tuple[int, str]]]:
    """The benchmark in blocks of bounded size. It is the stated query set; each block is shipped to the executors and costs one pass over the documents, so none is ever larger than block_chars, whatever the benchmark."""
    blocks: list[list[tuple[int, str]]] = [[]]
    size = 0
    for item_id, text in benchmark.select(id_col, text_col).where(f"{text_col} is not null").distinct().orderBy(id_col, text_col).toLocalIterator():
        if blocks[-1] and size + len(text) > block_chars:
            blocks.append([])
            size = 0
        blocks[-1].append((item_id, text))
        size += len(text)
    return blocks


_indexes: dict[tuple, ItemIndex] = {}


def _index(items: list[tuple[int, str]], rate: float, min_chars: int) -> ItemIndex:
    """Built once in each Python worker for each block."""
    key = (rate, min_chars, len(items), hash(tuple(items)))
    if key not in _indexes:
        _indexes.clear()
        _indexes[key] = ItemIndex(items, rate, min_chars)
    return _indexes[key]


MATCHES = "doc_id long, item_id long, edits int, start int, end int"


def matches(docs: DataFrame, blocks: list[list[tuple[int, str]]], *, rate: float = ERROR_RATE, min_chars: int = MIN_ITEM_CHARS) -> DataFrame:
    """One row for each document and item found in it: fewest edits, first of equals.

    Null and empty texts and items match nothing; repeated document rows give repeated matches.
    """

    def one(items):
        @tidy
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            index = _index(items, rate, min_chars)
            for df in batches:
                rows = [(d, *m) for d, t in zip(df["doc_id"], df["text"], strict=True) if isinstance(t, str) for m in index.find(t)]
                yield pd.DataFrame(rows, columns=["doc_id", "item_id", "edits", "start", "end"]).astype({"doc_id": "Int64", "item_id": "Int64", "edits": "int32", "start": "int32", "end": "int32"})

        return docs.select("doc_id", "text").where("text is not null").mapInPandas(run, MATCHES)

    out = one(blocks[0])
    for items in blocks[1:]:
        out = out.unionByName(one(items))
    return out


def clean(docs: DataFrame, blocks: list[list[tuple[int, str]]], *, rate: float = ERROR_RATE, min_chars: int = MIN_ITEM_CHARS, text_col: str = "text") -> DataFrame:
    """Documents that hold no item, all their columns; a narrow filter, no join."""
    def leaks_of(items):
        @F.pandas_udf("boolean")
        def leaks(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            index = _index(items, rate, min_chars)
            for texts in batches:
                yield pd.Series([isinstance(t, str) and bool(index.find(t)) for t in texts], dtype=bool)

        return leaks

    out = docs
    for items in blocks:
        out = out.where(~leaks_of(items)(F.col(text_col)))
    return out


def op4(spark, sf_dir: str) -> DataFrame:
    from llm.store import table

    return matches(table(spark, sf_dir, "documents"), item_blocks(table(spark, sf_dir, "benchmark")))
