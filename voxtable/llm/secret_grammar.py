"""Secret scans by grammar inference.

From labelled credentials a prefix tree is built for each format, and states whose continuations are statistically
compatible (Hoeffding bound on stopping and on each symbol, recursively) are merged, red-blue fashion, into a
probabilistic deterministic automaton. Every candidate token of a text is then scored: log-likelihood under
the best automaton against that of ordinary tokens, a character-pair model, per character. Candidates above the threshold
are added to the spans of the three base rules, which always stay.
"""

from __future__ import annotations

import bisect
import hashlib
import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from voxtable.llm.common import text_of

#: The base rules with the least length of what they find.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
LEAST_ASSIGN = 12
KINDS = ("assign", "access", "hex", "learned")
KEYWORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
RUN = "A-Za-z0-9+/_=.-"  # what credentials are made of
DELIMITERS = "+/_=.-"  # a credential may begin after one and end before one

_UPPER, _LOWER, _DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"
_ANY = _UPPER + _LOWER + _DIGITS
#: Public credential formats, each a sequence of literals and of (alphabet, lengths); labelled examples are drawn from them.
FORMATS = {
    "cloud_access": ("AKIA", (_UPPER + "234567", (16,))),
    "hex_digest": ((_DIGITS + "abcdef", (20, 32, 40, 64)),),
    "hex_upper": ((_DIGITS + "ABCDEF", (32, 40, 64)),),
    "forge_token": ("ghp_", (_ANY, (36,))),
    "chat_token": ("xoxb-", (_DIGITS, (10, 11, 12, 13)), "-", (_DIGITS, (12, 13)), "-", (_ANY, (24,))),
    "payment_key": ("sk_live_", (_ANY, (24,))),
    "base64_key": ((_ANY + "+/", (40, 43, 44, 64)),),
    "base64_one_pad": ((_ANY + "+/", (27, 43, 59)), "="),
    "base64_two_pads": ((_ANY + "+/", (22, 38, 42)), "=="),
    "signed_token": ("eyJ", (_ANY + "-_", (17, 33, 41)), ".eyJ", (_ANY + "-_", (20, 40, 60)), ".", (_ANY + "-_", (43,))),
}
PER_FORMAT = 200
ALPHA = 0.05
THRESHOLD = 1.2  # nats a character
SMOOTH = 0.1


def labelled(per_format: int = PER_FORMAT) -> dict[str, list[str]]:
    """Labelled credentials by format: the same on every run, letters drawn from a running digest."""
    out = {}
    for name, parts in FORMATS.items():
        out[name] = []
        for n in range(per_format):
            stream = (b for block in range(1 << 20) for b in hashlib.sha256(f"{name}:{n}:{block}".encode()).digest())
            drawn = [p if isinstance(p, str) else "".join(p[0][next(stream) % len(p[0])] for _ in range(p[1][(n + i) % len(p[1])])) for i, p in enumerate(parts)]
            out[name].append("".join(drawn))
    return out


def ordinary(per_kind: int = 2000) -> list[str]:
    """Tokens that are not credentials: syllable words, compounds, numbers, paths, names with numbers."""
    syllables = "an be ca de er fo ge he in jo ke la me no on pa qu re st ti un ver wi yo zu ing ion ment ble the sch ich heit keit lich ung ein pf tz ach chen eau oux elle tion tre ado mente ció llo que sta wh th ght str".split()
    out = []
    for n in range(per_kind):
        d = hashlib.sha256(f"ordinary:{n}".encode()).digest()
        word = lambda k, d=d: "".join(syllables[b % len(syllables)] for b in d[k : k + 3 + d[k] % 6])
        digits = "".join(str(b % 10) for b in d[:20])
        out += [word(0), word(1).capitalize(), f"{word(2)}-{word(9)}", f"{word(3)}_{word(12)}", word(4).upper(), digits[: 16 + d[0] % 8], f"{word(5)}/{word(11)}/{word(16)}", f"{word(6)}{d[7]}", "-" * (20 + d[1] % 20), "=" * (20 + d[1] % 20), f"20{digits[:2]}-{digits[2:4]}-{digits[4:6]}"]
    return out


class Automaton:
    """A probabilistic automaton learnt from strings; probability of a string from its start state."""

    def __init__(self, strings: Iterable[str], alpha: float = ALPHA):
        #: by state: strings that stop there, and by symbol [count, next state]
        self.stops: list[int] = [0]
        self.arcs: list[dict[str, list[int]]] = [{}]
        symbols = set()
        for s in strings:
            at = 0
            for c in s:
                symbols.add(c)
                if c not in self.arcs[at]:
                    self.arcs[at][c] = [0, len(self.arcs)]
                    self.stops.append(0)
                    self.arcs.append({})
                self.arcs[at][c][0] += 1
                at = self.arcs[at][c][1]
            self.stops[at] += 1
        self.alphabet = frozenset(symbols)
        self.symbols = len(symbols)
        self.bound = math.sqrt(0.5 * math.log(2 / alpha))
        self._merge_all()

    def _total(self, q: int) -> int:
        return self.stops[q] + sum(n for n, _ in self.arcs[q].values())

    def _alike(self, p: int, q: int) -> bool:
        """Recursive Hoeffding test on stopping and on every symbol."""
        todo = [(p, q)]
        while todo:
            p, q = todo.pop()
            n, m = self._total(p), self._total(q)
            if not n or not m:
                continue
            most = self.bound * (n**-0.5 + m**-0.5)
            if abs(self.stops[p] / n - self.stops[q] / m) > most:
                return False
            for c in self.arcs[p].keys() | self.arcs[q].keys():
                a, b = self.arcs[p].get(c), self.arcs[q].get(c)
                if abs((a[0] if a else 0) / n - (b[0] if b else 0) / m) > most:
                    return False
                if a and b and a[1] != b[1]:
                    todo.append((a[1], b[1]))
        return True

    def _explains(self, p: int, q: int) -> float:
        """Log-likelihood, smoothed, of the next symbols and stops of q under those of p."""
        n = self._total(p) + SMOOTH * (self.symbols + 1)
        seen = self.stops[q] * math.log((self.stops[p] + SMOOTH) / n) if self.stops[q] else 0.0
        return seen + sum(k * math.log((self.arcs[p].get(c, (0, 0))[0] + SMOOTH) / n) for c, (k, _) in self.arcs[q].items())

    def _fold(self, p: int, q: int) -> None:
        """Counts of the tree below q are added to p and what is below it."""
        todo = [(p, q)]
        while todo:
            p, q = todo.pop()
            self.stops[p] += self.stops[q]
            for c, (n, to) in self.arcs[q].items():
                if c in self.arcs[p]:
                    self.arcs[p][c][0] += n
                    todo.append((self.arcs[p][c][1], to))
                else:
                    self.arcs[p][c] = [n, to]

    def _merge_all(self) -> None:
        red = [0]
        blue = [(0, c) for c in sorted(self.arcs[0])]
        while blue:
            # the blue state most strings pass decides first
            blue.sort(key=lambda x: (self.arcs[x[0]][x[1]][0], x))
            p, c = blue.pop()
            q = self.arcs[p][c][1]
            alike = [r for r in red if self._alike(r, q)]
            # of compatible states the one under which what follows is likeliest: a prefix is not folded into what comes after it
            same = max(alike, key=lambda r: self._explains(r, q), default=None)
            if same is None:
                red.append(q)
            else:
                self.arcs[p][c][1] = same
                self._fold(same, q)
            known = set(red)
            blue = [(r, c) for r in red for c, (_, to) in sorted(self.arcs[r].items()) if to not in known]
        number = {q: n for n, q in enumerate(red)}
        stops, arcs, unseen = [], [], []
        for q in red:
            n = self._total(q) + SMOOTH * (self.symbols + 1)
            unseen.append(math.log(SMOOTH / n))
            stops.append(math.log((self.stops[q] + SMOOTH) / n))
            arcs.append({c: (math.log((k + SMOOTH) / n), number[to]) for c, (k, to) in self.arcs[q].items()})
        self.stop_scores, self.steps, self.unseen = stops, arcs, unseen

    def score(self, s: str) -> float:
        """Log-likelihood of the whole string; a symbol that a state has not seen costs its smoothed chance and stays; minus infinity outside the alphabet."""
        at, total = 0, 0.0
        for c in s:
            step = self.steps[at].get(c)
            if step is not None:
                total += step[0]
                at = step[1]
            elif c in self.alphabet:
                total += self.unseen[at]
            else:
                return -math.inf
        return total + self.stop_scores[at]


class Pairs:
    """Ordinary tokens: probability of each character after the one before."""

    def __init__(self, strings: Iterable[str]):
        counts: dict[str, Counter] = defaultdict(Counter)
        for s in strings:
            for a, b in zip("^" + s, s + "$", strict=True):
                counts[a][b] += 1
        self.scores = {a: {b: math.log((n + 0.1) / (sum(c.values()) + 7)) for b, n in c.items()} for a, c in counts.items()}
        self.other = {a: math.log(0.1 / (sum(c.values()) + 7)) for a, c in counts.items()}

    def step(self, a: str, b: str) -> float:
        row = self.scores.get(a)
        return row.get(b, self.other[a]) if row else -4.0

    def score(self, s: str) -> float:
        return sum(map(self.step, "^" + s, s + "$"))


class Grammar:
    """What is learnt: an automaton for each format, and the ordinary tokens' model."""

    def __init__(self, examples: dict[str, list[str]] | None = None, negatives: list[str] | None = None, threshold: float = THRESHOLD):
        examples = examples or labelled()
        self.formats = {name: Automaton(strings) for name, strings in examples.items()}
        self.plain = Pairs(negatives or ordinary())
        self.threshold = threshold
        sizes = [len(s) for strings in examples.values() for s in strings]
        #: no format has shorter credentials; what the automata loop over may be longer than any example
        self.least = min(sizes)
        self.runs = re.compile(f"[{RUN}]{{{self.least},}}")

    def likelihood(self, token: str) -> float:
        """Nats a character by which the best format explains the token better than ordinary text does."""
        best = max(a.score(token) for a in self.formats.values())
        return (best - self.plain.score(token)) / len(token) if best > -math.inf else -math.inf

    def best_from(self, run: str, begin: int, ends: list[int]) -> tuple[float, int] | None:
        """Of the candidates that begin here and end at one of the ends: the highest gain over ordinary text, in nats, and its end.

        All formats are run along the text at once, one step a character; each candidate end reads their stopping chances.
        """
        live = [(a, 0, 0.0) for a in self.formats.values()]
        plain, before, best, at = 0.0, "^", None, begin
        for end in ends:
            if not live:
                break
            while at < end:
                c = run[at]
                moved = []
                for a, q, total in live:
                    step = a.steps[q].get(c)
                    if step is not None:
                        moved.append((a, step[1], total + step[0]))
                    elif c in a.alphabet:
                        moved.append((a, q, total + a.unseen[q]))
                live = moved
                plain += self.plain.step(before, c)
                before, at = c, at + 1
                if not live:
                    break
            if live and end - begin >= self.least:
                gain = max(total + a.stop_scores[q] for a, q, total in live) - plain - self.plain.step(before, "$")
                if gain >= self.threshold * (end - begin) and (best is None or gain > best[0]):
                    best = gain, end
        return best

    def base_spans(self, text: str) -> list[tuple[int, int, int]]:
        """(start, kind, end) of the base rules, by start and kind."""
        found = []
        low = text.lower()
        if any(k in low for k in KEYWORDS):
            found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_ASSIGN]
        if "AKIA" in text:
            found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
        found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
        return sorted(found)

    def learned_spans(self, text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
        """Candidates above the threshold, best first, none overlapping another, that no base span covers whole.

        A candidate begins where a run of credential characters does or after a delimiter in it, and ends likewise.
        """
        out, covers, reach = [], iter(base), []
        coming = next(covers, None)
        for m in self.runs.finditer(text):
            run, at = m[0], m.start()
            cuts = [i for i, c in enumerate(run) if c in DELIMITERS]
            ends = [i for i in [*cuts, len(run)] if i]
            # padding belongs to what it ends
            ends = sorted({*ends, *(i + 1 for i in cuts if run[i] == "=")})
            begins = [0, *(i + 1 for i in cuts if i + 1 < len(run) and run[i + 1] not in DELIMITERS)]
            found = []
            for b in begins:
                if len(run) - b < self.least:
                    break
                if (best := self.best_from(run, b, ends[bisect.bisect_left(ends, b + 1) :])) is not None:
                    found.append((best[0], b, best[1]))
            while coming is not None and coming[0] < at + len(run):  # both lists are in order
                reach.append((coming[0], coming[2]))
                coming = next(covers, None)
            reach = [(s, e) for s, e in reach if e > at]
            taken: list[tuple[int, int]] = []
            for _, b, e in sorted(found, key=lambda f: (-f[0], f[1])):
                i = bisect.bisect_left(taken, (b, e))
                if (i and taken[i - 1][1] > b) or (i < len(taken) and taken[i][0] < e):
                    continue
                taken.insert(i, (b, e))
                if not any(s <= at + b and at + e <= t for s, t in reach):
                    out.append((at + b, 3, at + e))
        return sorted(out)


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


COLUMNS = "n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_learned long"


def scan_batch(grammar: Grammar, texts: Iterable[str]) -> pd.DataFrame:
    rows = []
    for text in texts:
        base = grammar.base_spans(text)
        more = grammar.learned_spans(text, base)
        kinds = Counter(k for _, k, _ in base)
        rows.append((kinds[0], kinds[1], kinds[2], hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(sorted(base + more)), len(more)))
    return pd.DataFrame(rows, columns=["n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_learned"])


def secret_spans(docs: DataFrame, grammar: Grammar | None = None) -> DataFrame:
    """doc_id and the spans of secrets in every row's whole text: counts of the base rules, their digest, all spans.

    Spans are of code points, end exclusive; a base span is its rule's whole match. Null counts as empty and has none. Rows that repeat
    a doc_id get a row each; an empty table gives an empty result; other columns are not read. Texts of any length are read whole, in time by their length.
    Of candidates that overlap the one of the highest gain is taken, of equal ones the first. The grammar is learnt
    by the driver from labelled credentials, a fixed number, and goes with the task.
    """
    grammar = grammar or Grammar()

    def scan(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield scan_batch(grammar, batch)

    scan.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.DataFrame]}
    scanned = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.pandas_udf(scan, COLUMNS)(text_of()).alias("s"))
    return scanned.select("doc_id", "s.*")
