"""Token counts by a compiled finite-state tokenizer.

A byte-pair tokenizer is run left to right: the tokens of a prefix end in exactly one last token, and a token may follow
another if their concatenation is itself split into just these two. So all that matters of the text read so far is, for
each suffix that still begins some token, that suffix, the last token before it and the tokens counted since:
finitely many states. They are compiled, when first reached, into a deterministic transducer whose transitions are
annotated with the change of the token count (it falls where tokens merge).

No token spans the start of a word mark that follows another character, nor an unknown character, so there every
state falls into a few. Text between such points is a chunk; a chunk's state map is the count it adds and the state it ends in,
cached by its string. A text's chunks compose associatively, in a pairwise (parallel prefix) scan.
"""

from __future__ import annotations

import gc
import re
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from voxtable.llm.common import text_of

#: Fixed value: the mark that this kind of tokenizer writes for a space.
MARK = "▁"
LIMIT = 4096
NEVER = -float("inf")
SLICE = 1 << 20  # characters mapped at once
STATES, CHUNKS, PAIRS = 1 << 18, 1 << 19, 1 << 20  # kept by each worker: some 400 MB


_SHARED: dict[bytes, "Transducer"] = {}


class Chunks(dict):
    """Counts by chunk; a missing one is computed."""

    def __init__(self, count: Callable[[str], int]):
        self.count = count

    def __missing__(self, part: str) -> int:
        if len(self) >= CHUNKS:
            self.clear()
        n = self[part] = self.count(part)
        return n


class Transducer:
    """Counts the tokens of a byte-pair model with byte fallback: scores by piece, pieces of other kinds left out."""

    def __init__(self, scores: dict[str, float]):
        self.scores = scores
        self.prefixes = {p[:i] for p in scores for i in range(1, len(p) + 1)}
        self.pairs: dict[tuple[str | None, str], bool] = {}
        self.spines: dict[tuple[str, bool], list[tuple[str, float]]] = {}
        self.ids: dict[tuple, int] = {}
        self.states: list[tuple] = []
        self.arcs: list[dict[str, tuple[int, int]]] = []
        self.start = self._state((("", None, 0),))
        self._closed = Chunks(self._counted).__getitem__
        known = "".join(re.escape(c) for c in sorted({c for p in scores for c in p} - {MARK}))
        # a chunk: marks and the known characters after them, or characters that no token holds
        self.chunk = re.compile(f"{MARK}+[{known}]*|[{known}]+|[^{MARK}{known}]+")

    @classmethod
    def from_model(cls, model: bytes) -> Transducer:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        plain = (i for i in range(sp.get_piece_size()) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i)))
        return cls({sp.id_to_piece(i): sp.get_score(i) for i in plain})

    @classmethod
    def shared(cls, model: bytes) -> Transducer:
        """One for each worker process and model: what is compiled serves later tasks too."""
        if model not in _SHARED:
            _SHARED.clear()
            _SHARED[model] = cls.from_model(model)
        return _SHARED[model]

    def _spine(self, token: str, right: bool) -> list[tuple[str, float]]:
        """What a token's last (or first) character belongs to as the token is merged, each with the score of the merge that ends it."""
        key = (token, right)
        if (known := self.spines.get(key)) is not None:
            return known
        parts, spine = list(token), []
        while len(parts) > 1:
            best, left = max((self.scores.get(x + y, NEVER), -i) for i, (x, y) in enumerate(zip(parts, parts[1:], strict=False)))
            if best == NEVER:
                break
            i = -left
            if i + 2 == len(parts) if right else i == 0:
                spine.append((parts[-1] if right else parts[0], best))
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        if len(parts) > 1:
            spine = []  # the model never makes this token
        else:
            spine.append((token, NEVER))
        self.spines[key] = spine
        return spine

    def _may_follow(self, last: str | None, token: str) -> bool:
        """Whether the two, side by side, stay two: no merge across the seam comes before those within."""
        key = (last, token)
        if (known := self.pairs.get(key)) is None:
            a = [("", NEVER)] if last is None else self._spine(last, True)
            b = self._spine(token, False)
            known = bool(a and b)
            i = j = 0
            while known:
                across = self.scores.get(a[i][0] + b[j][0], NEVER) if last is not None else NEVER
                one, two = a[i][1], b[j][1]
                if across != NEVER and across > one and across >= two:  # equals fall to the left
                    known = False
                elif one == NEVER and two == NEVER:
                    break
                elif one >= two:
                    i += 1
                else:
                    j += 1
            self.pairs[key] = known
        return known

    def _state(self, state: tuple) -> int:
        if (n := self.ids.get(state)) is None:
            n = self.ids[state] = len(self.states)
            self.states.append(state)
            self.arcs.append({})
        return n

    def _arc(self, state: int, c: str) -> tuple[int, int]:
        """Next state and change of count."""
        if c not in self.scores:  # falls back to a token for each byte; no token holds it
            return self.start, len(c.encode("utf-8", "surrogatepass"))
        grown, delta, token = [], 0, None
        for s, last, n in self.states[state]:
            s += c
            if s in self.prefixes:
                grown.append((s, last, n))
                if token is None and s in self.scores and self._may_follow(last, s):
                    token, delta = s, n + 1
        ahead = [(s, None if last and s[0] == MARK and last[-1] != MARK else last, n - delta) for s, last, n in grown]
        ahead.append(("", token, 0))
        return self._state(tuple(ahead)), delta

    def run(self, state: int, text: str) -> tuple[int, int]:
        """State map of a chunk, from one state: (end state, tokens added)."""
        count = 0
        for c in text:
            arcs = self.arcs[state]
            if (arc := arcs.get(c)) is None:
                arc = arcs[c] = self._arc(state, c)
            state = arc[0]
            count += arc[1]
        return state, count

    def chunk_map(self, chunk: str) -> tuple[str, int, str]:
        """A chunk's map whatever the state before: (head to be run from that state, count after it, tail not yet closed)."""
        parts = self.chunk.findall(chunk)
        if len(parts) < 2:
            return chunk, 0, ""
        return parts[0], sum(map(self._closed, parts[1:-1])), parts[-1]

    def _counted(self, part: str) -> int:
        """Tokens of a whole chunk; the compiled part and the chunks kept are emptied when full, and grow anew as needed."""
        if len(self.states) >= STATES:
            self.ids.clear()
            self.states.clear()
            self.arcs.clear()
            self.start = self._state((("", None, 0),))
        if len(self.pairs) >= PAIRS:
            self.pairs.clear()
        return self.run(self.start, part)[1]

    def compose(self, a: tuple[str, int, str], b: tuple[str, int, str]) -> tuple[str, int, str]:
        """The map of two neighbouring slices: associative, so slices may be composed in any bracketing."""
        seam = self.chunk.findall(a[2] + b[0]) if a[2] else None
        if seam is None:  # a is a single open chunk
            whole = self.chunk_map(a[0] + b[0])
            if not b[2]:
                return whole
            return (whole[0], whole[1] + (self._closed(whole[2]) if whole[2] else 0) + b[1], b[2]) if whole[2] else (whole[0], b[1], b[2])
        if not b[2]:  # b is a single open chunk
            return a[0], a[1] + sum(map(self._closed, seam[:-1])), seam[-1]
        return a[0], a[1] + sum(map(self._closed, seam)) + b[1], b[2]

    def count(self, text: str) -> int:
        """Tokens of a whole text: its slices' maps, composed pair by pair."""
        if not text:
            return 0
        text = MARK + text.replace(" ", MARK)
        maps = [self.chunk_map(text[i : i + SLICE]) for i in range(0, len(text), SLICE)]
        while len(maps) > 1:
            maps = [self.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        head, n, tail = maps[0]
        return self._closed(head) + n + (self._closed(tail) if tail else 0)


def token_counts(docs: DataFrame, model_path: str, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row, as the model at model_path tokenizes whole texts.

    Null counts as empty: no bytes, no tokens. Texts of any length are read in slices. Rows that repeat a doc_id get a row
    each; an empty table gives an empty result; other columns are not read. The model's file (under a MB) is read by the driver and goes with the task.
    """
    with open(model_path, "rb") as f:
        model = f.read()

    def counts(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        fst = Transducer.shared(model)
        for batch in batches:
            yield pd.Series([fst.count(t) for t in batch], dtype="int64")
            gc.freeze()  # what is compiled stays: the collector need not walk it again

    counted = F.pandas_udf(_typed(counts), "long")
    text = text_of()
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.octet_length(text).cast("long").alias("n_bytes"), counted(text).alias("n_tokens"))
    return rows.withColumn("over_limit", F.col("n_tokens") > limit)


def _typed(f):  # noqa: ANN001, ANN202
    """The hints that Spark reads, as classes rather than as this module's deferred strings."""
    f.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return f

