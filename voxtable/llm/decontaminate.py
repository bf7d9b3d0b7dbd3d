"""Benchmark decontamination by pigeonhole edit matching.

Items and documents are normalised to lower-case words with single blanks. An item of m characters has an error
budget k = floor(RATE x m) and is split into k + 1 pieces: a passage within k edits of the item holds at least
one piece unchanged. One automaton over all pieces finds every exact hit in a pass over the text; around hits
the item is verified with Myers' bit-parallel distance, a whole column of the dynamic programme in one integer.

The query set is the benchmark. It goes to the documents in blocks of at most BLOCK_CHARS characters, each checked as
it is read, so what a task holds is bounded however large the benchmark is; documents are neither shuffled nor grouped.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from voxtable.llm.common import broadcast_if_small, columns_of, cut, text_of

RATE = 0.06
BLOCK_CHARS = 4_000_000
SLICE = 1 << 20  # characters of a text searched at once
_WORD = re.compile(r"[^\W_]+")
HITS = "doc_id long, item_id long, distance int, budget int, span_start long, span_end long"


def normalise(text: str) -> str:
    """Words in lower case between single blanks: cut first, so places of words in the text are places of words here."""
    return " ".join(_WORD.findall(text)).lower()


def pieces(item: str, budget: int) -> list[tuple[int, str]]:
    """budget + 1 pieces of even length, each with its place in the item."""
    n = budget + 1
    cuts = [len(item) * i // n for i in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


class Myers:
    """Distance of a pattern to the best substring ending at each place of a text."""

    def __init__(self, pattern: str):
        self.m = len(pattern)
        self.masks: dict[str, int] = {}
        for i, c in enumerate(pattern):
            self.masks[c] = self.masks.get(c, 0) | 1 << i
        self.all, self.top = (1 << self.m) - 1, 1 << self.m - 1

    def best(self, text: str) -> tuple[int, int]:
        """(least distance, first end where it is reached)."""
        up, down, score = self.all, 0, self.m
        least, end = score, 0
        for j, c in enumerate(text):
            eq = self.masks.get(c, 0)
            x = eq | down
            d0 = ((((eq & up) + up) ^ up) | x) & self.all
            hp = down | ~(d0 | up) & self.all
            hn = up & d0
            if hp & self.top:
                score += 1
            elif hn & self.top:
                score -= 1
            hp, hn = hp << 1, hn << 1  # a match may start anywhere: row zero stays zero
            up = (hn | ~(d0 | hp)) & self.all
            down = hp & d0 & self.all
            if score < least:
                least, end = score, j + 1
        return least, end


class Matcher:
    """The pieces of a block of items, and how to verify an item around a hit."""

    def __init__(self, items: list[tuple[int, str]], rate: float = RATE):
        import ahocorasick

        self.items = [(i, t, int(rate * len(t))) for i, t in ((i, normalise(t)) for i, t in items) if t]
        self.automaton = ahocorasick.Automaton()
        homes: dict[str, list[tuple[int, int]]] = {}
        for n, (_, text, budget) in enumerate(self.items):
            for at, piece in pieces(text, budget):
                homes.setdefault(piece, []).append((n, at))
        for piece, of in homes.items():
            self.automaton.add_word(piece, (len(piece), of))
        if homes:
            self.automaton.make_automaton()
        self.longest = max((len(t) + 2 * k for _, t, k in self.items), default=0)
        self.forward = [Myers(t) for _, t, _ in self.items]

    def _windows(self, text: str) -> dict[int, list[list[int]]]:
        """By item: the stretches of text that hold every passage around its hits, overlapping ones joined."""
        spans: dict[int, list[list[int]]] = {}
        for last, (size, of) in self.automaton.iter(text):
            begin = last + 1 - size
            for n, at in of:
                _, item, budget = self.items[n]
                lo, hi = max(0, begin - at - budget), begin - at + len(item) + budget
                mine = spans.setdefault(n, [])
                if mine and lo <= mine[-1][1] and mine[-1][1] - mine[-1][0] < 4 * self.longest:
                    mine[-1] = [min(lo, mine[-1][0]), max(hi, mine[-1][1])]
                else:
                    mine.append([lo, hi])
        return spans

    def matches(self, raw: str) -> list[tuple[int, int, int, int, int]]:
        """(item_id, distance, budget, start, end) of the best passage of each item within its budget; places in the raw text."""
        if not self.items:
            return []
        text = normalise(raw)
        best: dict[int, tuple[int, int]] = {}
        for n, windows in self._windows(text).items():
            budget = self.items[n][2]
            for lo, hi in windows:
                distance, end = self.forward[n].best(text[lo:hi])
                if distance <= budget and distance < best.get(n, (budget + 1, 0))[0]:
                    best[n] = (distance, lo + end)
                if distance == 0:
                    break
        if not best:
            return []
        # places of the normalised words in the raw text
        words, at = [], 0
        for m in _WORD.finditer(raw):
            size = len(m[0].lower())
            words.append((at, at + size, m.start(), m.end()))
            at += size + 1
        out = []
        for n, (distance, end) in best.items():
            item_id, item, budget = self.items[n]
            _, back = Myers(item[::-1]).best(text[max(0, end - len(item) - budget) : end][::-1])
            begin = end - back
            over = [w for w in words if w[0] < end and w[1] > begin]
            out.append((item_id, distance, budget, over[0][2] if over else 0, over[-1][3] if over else 0))
        return out


def _blocks(items: DataFrame, most: int) -> Iterator[list[tuple[int, str]]]:
    block, size = [], 0
    for item_id, text in items.select(F.col("item_id").cast("long"), text_of()).toLocalIterator():
        if block and size + len(text) > most:
            yield block
            block, size = [], 0
        block.append((item_id, text))
        size += len(text)
    if block:
        yield block


def leaks(docs: DataFrame, items: DataFrame, rate: float = RATE, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """One row for each document and item that it holds within the error budget: doc_id, item_id, distance, budget, span_start, span_end.

    The span is in code points of the document's raw text. Null and empty texts hold nothing; items without a word match nothing; an item
    shorter than 1 / rate characters must occur exactly. Repeated items and rows give a row each. Empty tables give an empty
    result; other columns are not read. Of an item's passages in a document the nearest is reported, of equally near ones the first. Texts of any length
    are searched whole, in time by their length.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"))
    found = None
    for block in _blocks(items, block_chars):
        shared = docs.sparkSession.sparkContext.broadcast(block)

        def search(batches: Iterator[pd.DataFrame], shared=shared) -> Iterator[pd.DataFrame]:  # noqa: ANN001
            matcher = Matcher(shared.value, rate)
            for batch in batches:
                hits = [(d, *m) for d, t in zip(batch["doc_id"], batch["text"], strict=True) for m in matcher.matches(t)]
                out = pd.DataFrame(hits, columns=["doc_id", "item_id", "distance", "budget", "span_start", "span_end"])
                yield out.astype({"doc_id": "Int64", "item_id": "Int64"})

        hits = rows.mapInPandas(search, HITS)
        found = hits if found is None else found.unionAll(hits)
    if found is None:
        return docs.sparkSession.createDataFrame([], HITS)
    return found


def without_leaks(docs: DataFrame, items: DataFrame, rate: float = RATE) -> DataFrame:
    """The documents of docs that hold no item; rows without a doc_id stay; columns as in docs."""
    leaking = cut(leaks(docs, items, rate).select("doc_id").distinct())
    return docs.join(broadcast_if_small(leaking, 1_000_000), "doc_id", "left_anti").select(*columns_of(docs))
