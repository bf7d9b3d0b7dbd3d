"""Toxicity by a subsequence string kernel, Nyström landmarks and a support vector machine.

Two words are compared by the gap-weighted kernel over their subsequences of three letters, the word's beginning counting as one, so an insult
is still near itself with characters inserted, left out or set apart. Landmarks are words that labelled toxic documents hold and others do
not, and frequent words of the others. In the Nyström map of the landmarks a linear machine is trained on
words of labelled sentences; which word makes a toxic document toxic is not labelled, so the highest scored one of each is taken, in
rounds (multiple-instance learning). A document scores by its highest word, through a logistic curve fitted on the same sample.

The machine is linear in the kernel, hence in the subsequence features: its weights are folded into one table of
32**3 numbers, and scoring a word is a lookup and sum. Distinct words of a batch are scored once, as whole arrays.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from voxtable.llm.common import text_of

SAMPLE = 3_500  # labelled documents that a model is fitted on, at most
SAMPLE_CHARS = 40_000  # the sample is drawn from labelled documents of at most so many characters: with SAMPLE it bounds what the driver holds
DECAY = 0.6
SPAN = 24  # letters of a word compared at once, its beginning included; longer words by stretches
STRIDE = 6  # from stretch to stretch: what lies within SPAN - STRIDE letters is whole in one
BEGIN = "^"  # marks where a word begins; no word holds it
TOXIC_LANDMARKS, PLAIN_LANDMARKS = 96, 48
NEGATIVES = 12_000
STEMS, STEM, KIN = (4, 5, 6), "*", 3  # lengths of beginnings that evidence is gathered for, their mark, landmarks of one beginning
SURE = 3.0  # nats of evidence for a landmark, beyond those that the number of words asks for
ROUNDS = 4
PURE = 0.1  # most odds, against those of toxic documents, at which plain ones hold a toxic word
NEAR = 0.3  # least decision value of a word taken for a document's toxic one
WARNED = -1.0  # least decision value of a plain document's highest word that is trained on once more
THRESHOLD = 0.7
CACHE = 1 << 18
TOGETHER = 1 << 20  # characters whose words are in memory at once
#: ASCII characters that are no letter and no white space: they go before words are cut.
_OUTSIDE = bytes(i for i in range(128) if not chr(i).isalpha() and not chr(i).isspace())
_SPELT = re.compile(r"(?<!\S)(?:\S\s){3,}\S(?!\S)")


def words_of(text: str) -> list[str]:
    """Words between white space, their letters only; letters set apart by single blanks count as one word as well."""
    text = text.lower().encode("utf-8", "replace").translate(None, _OUTSIDE).decode()
    return text.split() + ["".join(m.split()) for m in _SPELT.findall(text)]


_GRIDS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _grid(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of all subsequences of three in a word of n letters, and their weights."""
    if n not in _GRIDS:
        at = np.array(list(combinations(range(n), 3)), dtype=np.int64)
        _GRIDS[n] = at, DECAY ** (at[:, 2] - at[:, 0] + 1)
    return _GRIDS[n]


def _codes(words: list[str], n: int) -> np.ndarray:
    """Subsequences of words of n letters, each as a number below 2**15: letters are 1..26, others 27..31, the beginning 0."""
    at, _ = _grid(n)
    points = np.array(words, dtype=f"<U{n}").view(np.uint32).reshape(len(words), n).astype(np.int32)
    c = np.where((points >= 97) & (points < 123), points - 96, np.where(points == ord(BEGIN), 0, 27 + points % 5))
    return (c[:, at[:, 0]] << 10) | (c[:, at[:, 1]] << 5) | c[:, at[:, 2]]


def features(words: list[str], n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of words of n letters: subsequence codes and weights, (word, place) each, and the norms of their feature vectors."""
    _, weight = _grid(n)
    codes = _codes(words, n)
    order = np.argsort(codes, axis=1, kind="stable")
    runs = np.take_along_axis(codes, order, axis=1)
    sums = weight[order].cumsum(axis=1)
    last = np.ones_like(runs, dtype=bool)
    last[:, :-1] = runs[:, 1:] != runs[:, :-1]
    row, col = np.nonzero(last)
    ends = sums[row, col]
    first = np.r_[True, row[1:] != row[:-1]]
    each = ends - np.where(first, 0.0, np.r_[0.0, ends[:-1]])
    norms = np.sqrt(np.bincount(row, each * each, minlength=len(words)))
    return codes, np.broadcast_to(weight, codes.shape), norms


def dense(words: list[str]) -> np.ndarray:
    """Unit feature vectors of a bounded list of words, of any length from three to SPAN letters."""
    out = np.zeros((len(words), 1 << 15), dtype=np.float32)
    for n in {len(w) for w in words}:
        where = [i for i, w in enumerate(words) if len(w) == n]
        codes, weight, norms = features([words[i] for i in where], n)
        for i, c, w, norm in zip(where, codes, weight, norms, strict=True):
            np.add.at(out[i], c, w / norm)
    return out


def kernel(words: list[str], marks: np.ndarray) -> np.ndarray:
    """Normalised kernel of words of three to SPAN letters against landmarks given as rows of features."""
    table = np.ascontiguousarray(marks.T)
    out = np.zeros((len(words), len(marks)))
    for n in {len(w) for w in words}:
        where = np.array([i for i, w in enumerate(words) if len(w) == n])
        step = max(1, 20_000 // len(_grid(n)[0]))
        for s in range(0, len(where), step):
            some = where[s : s + step]
            codes, weight, norms = features([words[i] for i in some], n)
            out[some] = np.einsum("bcl,c->bl", table[codes], weight[0].astype(np.float32)) / norms[:, None]
    return out


def _squared_hinge(x: np.ndarray, y: np.ndarray, cost: np.ndarray, ridge: float = 1.0, steps: int = 20) -> tuple[np.ndarray, float]:
    """Linear machine by Newton steps on the squared hinge loss."""
    x1 = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x1.shape[1])
    keep = np.full(x1.shape[1], ridge)
    keep[-1] = 1e-3
    for _ in range(steps):
        margin = y * (x1 @ w)
        inside = margin < 1
        xs, ys, cs = x1[inside], y[inside], cost[inside]
        grad = keep * w - 2 * xs.T @ (cs * ys * (1 - margin[inside]))
        hess = np.diag(keep) + 2 * (xs * cs[:, None]).T @ xs
        step = np.linalg.solve(hess, grad)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w[:-1], w[-1]


def stretches(word: str) -> list[str]:
    """A word of three letters and more as what is compared at once: itself, its beginning marked, or overlapping parts of it."""
    word = BEGIN + word
    return [word[s : s + SPAN] for s in range(0, max(1, len(word) - SPAN + STRIDE), STRIDE)]


#: Word bounds and values by model, kept by a worker process from task to task; the last model's alone.
_SHARED: dict[int, tuple[dict[str, float], dict[str, float]]] = {}


class Model:
    """Weights by subsequence, bias and logistic curve; scores words and texts."""

    def __init__(self, table: np.ndarray, bias: float, slope: float, offset: float, nothing: float | None = None):
        self.table, self.bias, self.slope, self.offset = table, bias, slope, offset
        self.nothing = bias if nothing is None else nothing  # value of a text without words
        key = hash((table.tobytes(), bias))
        if key not in _SHARED:
            _SHARED.clear()
            _SHARED[key] = {}, {}
        self.bounds, self.exact = _SHARED[key]

    def __reduce__(self) -> tuple:
        return Model, (self.table, self.bias, self.slope, self.offset, self.nothing)

    def _each(self, words: list[str], value) -> list[float]:  # noqa: ANN001
        """The highest value among each word's stretches; value(stretches of n letters) gives theirs."""
        out = np.full(len(words), -np.inf)
        by_size: dict[int, list[tuple[int, str]]] = {}
        for i, w in enumerate(words):
            for part in stretches(w):
                by_size.setdefault(len(part), []).append((i, part))
        for n, of in by_size.items():
            step = max(1, 500_000 // len(_grid(n)[0]))
            for s in range(0, len(of), step):
                some = of[s : s + step]
                np.maximum.at(out, [i for i, _ in some], value([w for _, w in some], n))
        return out.tolist()

    def _bound(self, parts: list[str], n: int) -> np.ndarray:
        """No less than the decision values: a vector's norm is no less than that of distinct weights and no more than their sum."""
        weight = _grid(n)[1]
        sums = self.table[_codes(parts, n)] @ weight
        return np.where(sums > 0, sums / np.sqrt(weight @ weight), sums / weight.sum()) + self.bias

    def _value(self, parts: list[str], n: int) -> np.ndarray:
        codes, weight, norms = features(parts, n)
        return self.table[codes] @ weight[0] / norms + self.bias

    def raw(self, words: list[str]) -> np.ndarray:
        """Decision values of words of three letters and more."""
        return np.array(self._each(words, self._value))

    def values(self, texts: Iterable[str]) -> np.ndarray:
        """The highest decision value among each text's words of three letters and more; the least known value without any."""
        out, some, size = [], [], 0
        for t in texts:
            some.append(t)
            size += len(t)
            if size >= TOGETHER:
                out.append(self._values(some))
                some, size = [], 0
        return np.concatenate([*out, self._values(some)])

    def _values(self, texts: list[str]) -> np.ndarray:
        split = [{w for w in words_of(t) if len(w) >= 3} for t in texts]
        if len(self.bounds) > CACHE:
            self.bounds.clear()
            self.exact.clear()
        new = sorted(set().union(*split) - self.bounds.keys())
        self.bounds.update(zip(new, self._each(new, self._bound), strict=True))
        # words by falling bound; a text is done when its next word's bound is no higher than its best value
        queues = [sorted(ws, key=self.bounds.__getitem__) for ws in split]
        best = np.full(len(texts), -np.inf)
        todo = list(range(len(texts)))
        while todo:
            asked = {i: [queues[i].pop() for _ in range(min(4, len(queues[i])))] for i in todo}
            new = sorted({w for ws in asked.values() for w in ws} - self.exact.keys())
            self.exact.update(zip(new, self.raw(new).tolist(), strict=True))
            for i, ws in asked.items():
                best[i] = max([best[i], *map(self.exact.__getitem__, ws)])
            todo = [i for i in todo if queues[i] and self.bounds[queues[i][-1]] > best[i]]
        return np.where(np.isfinite(best), best, self.nothing)

    def scores(self, texts: Iterable[str]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.values(texts) * self.slope + self.offset, -50, 50)))


def keys_of(word: str) -> list[str]:
    """A word, and its beginnings."""
    return [word, *(word[:k] + STEM for k in STEMS if len(word) > k)]


def fit(texts: list[str], toxic: list[int]) -> Model:
    """A model from labelled texts. Without both labels: one that scores every text by the share of toxic ones, nearly."""
    y = np.array(toxic)
    bags = [sorted({p for p in words_of(t) if 3 <= len(p) < SPAN}) for t in texts]
    if not len(y) or y.min() == y.max():
        return Model(np.zeros(1 << 15), 0.0, 0.0, 10.0 if len(y) and y.min() else -10.0)
    # a fifth, chosen by its texts' hashes, is kept for the curve
    kept = np.array([hash_of(t) % 5 == 0 for t in texts])
    if min(y[kept].sum(), (1 - y[kept]).sum(), y[~kept].sum(), (1 - y[~kept]).sum()) < 5:
        kept, learnt = np.ones(len(y), dtype=bool), np.ones(len(y), dtype=bool)  # too few for two parts
    else:
        learnt = ~kept
    kept_texts, kept_y = [t for t, k in zip(texts, kept, strict=True) if k], y[kept]
    bags, y = [b for b, k in zip(bags, learnt, strict=True) if k], y[learnt]
    yes, no = Counter(), Counter()
    for bag, t in zip(bags, y, strict=True):
        (yes if t else no).update({key for w in bag for key in keys_of(w)})
    n_yes, n_no = int(y.sum()), int(len(y) - y.sum())
    base, most = n_yes / len(y), np.log(len(yes) + 1) + SURE

    def gain(w: str) -> float:
        """Evidence, in nats, that the word, or what begins like it, is commoner in toxic documents."""
        n, k = yes[w] + no[w], yes[w]
        return k * np.log(k / n / base) + (no[w] * np.log(no[w] / n / (1 - base)) if no[w] else 0.0) if k / n > base else 0.0

    # a word stands for the strongest of itself and its beginnings; of the words of one beginning, KIN
    distinct = sorted(w for w in yes.keys() | no.keys() if not w.endswith(STEM))
    told = {w: max((gain(k), k) for k in keys_of(w)) for w in distinct if yes[w]}
    family: dict[str, list[str]] = {}
    for w in sorted(told, key=lambda w: (-told[w][0], -yes[w], w)):
        family.setdefault(told[w][1], []).append(w)
    hot = [w for ws in family.values() for w in ws[:KIN] if told[w][0] > most]
    calm = sorted((w for w in distinct if no[w]), key=lambda w: (-no[w], w))
    hot = hot[:TOXIC_LANDMARKS] or sorted(told, key=lambda w: (-told[w][0], w))[:4]
    landmarks = [*hot, *[w for w in calm if w not in set(hot)][:PLAIN_LANDMARKS]]
    marked = lambda words: [BEGIN + w for w in words]
    marks = dense(marked(landmarks))
    values, vectors = np.linalg.eigh((marks @ marks.T).astype(np.float64))
    good = values > 1e-6
    half = vectors[:, good] / np.sqrt(values[good])
    mapped = lambda words: kernel(marked(words), marks) @ half
    # plain words: the most frequent half, and a spread over the rest
    rest = sorted(calm[NEGATIVES // 2 :], key=lambda w: hash_of(w))[: NEGATIVES // 2]
    plain = [*calm[: NEGATIVES // 2], *rest]
    x_no = mapped(plain)
    firm = [w for w in hot if no[w] * n_yes < PURE * yes[w] * n_no] or hot
    known, hard, model = set(firm), Counter(), None
    for _ in range(ROUNDS):
        pos, neg = sorted(known), sorted(hard)
        x = np.vstack([mapped(pos), x_no, *([mapped(neg)] if neg else [])])
        target = np.r_[np.ones(len(pos)), -np.ones(len(x_no) + len(neg))]
        cost = np.r_[np.array([1.0 + np.log1p(yes[w]) for w in pos]), np.ones(len(x_no)), np.array([1.0 + hard[w] for w in neg])]
        w, bias = _squared_hinge(x, target, cost)
        model = Model((half @ w) @ marks.astype(np.float64), float(bias), 1.0, 0.0)
        # the highest word of every document: a toxic one's if no plain document holds it often, a plain one's as a warning
        known = set(firm)
        value = dict(zip(distinct, model.raw(distinct).tolist(), strict=True))
        for bag, t in zip(bags, y, strict=True):
            mine = [v for v in bag if no[v] * n_yes < PURE * yes[v] * n_no] if t else bag
            if mine:
                top = max(mine, key=value.__getitem__)
                if t and value[top] > NEAR:
                    known.add(top)
                elif not t and value[top] > WARNED:
                    hard[top] += 1
    calibrate(model, model.values(kept_texts), kept_y)
    return model


def calibrate(model: Model, values: np.ndarray, y: np.ndarray) -> None:
    """A logistic curve through documents that the weights were not learnt from; at THRESHOLD stands the value that parts them best (F1)."""
    n_yes, n_no = int(y.sum()), int(len(y) - y.sum())
    x1 = np.stack([values, np.ones(len(y))], axis=1)
    t = np.where(y == 1, (n_yes + 1) / (n_yes + 2), 1 / (n_no + 2))
    ridge = np.array([1e-3, 1e-4])
    beta = np.array([1.0, 0.0])
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x1 @ beta, -30, 30)))
        hess = (x1 * (p * (1 - p))[:, None]).T @ x1 + np.diag(ridge)
        step = np.linalg.solve(hess, x1.T @ (p - t) + ridge * beta)
        beta -= np.clip(step, -2, 2)
    model.slope = max(float(beta[0]), 1e-3)
    model.nothing = float(min(model.bias, values.min()))
    order = np.argsort(-values, kind="stable")
    v, hit = values[order], np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(v) + 1) + n_yes)
    f1[:-1][v[:-1] == v[1:]] = -1  # equal values fall on one side
    best = int(np.argmax(f1))
    at = (v[best] + v[best + 1]) / 2 if best + 1 < len(v) else v[best]
    model.offset = float(np.log(THRESHOLD / (1 - THRESHOLD)) - model.slope * at)


def hash_of(word: str) -> int:
    import zlib

    return zlib.crc32(word.encode())


def held_out(doc_id: Column) -> Column:
    """The fold that no label is learnt from."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 3 == 1, F.lit(False))


def fit_on(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """A model from a bounded sample, in hash order, of labelled documents outside the held-out fold."""
    short = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text")).filter(F.char_length("text") <= SAMPLE_CHARS)
    truth = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").alias("toxic"))
    chosen = truth.filter(~held_out(F.col("doc_id"))).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    # of rows that repeat a doc_id one text: what reaches the driver is SAMPLE texts of SAMPLE_CHARS
    rows = short.join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text")).toPandas().sort_values("doc_id")
    return fit(list(rows["text"]), [int(t) for t in rows["toxic"]])


def score(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted for every row: whole texts, nothing but the text.

    Null and empty texts and texts without a word of three letters score as the least toxic text known. Rows that repeat a doc_id score each; null doc_id
    is not held out; an empty table gives an empty result; other columns are not read. Texts of any length are scored whole, in time by their length.
    """

    def scored(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series(model.scores(batch), dtype="float64")

    scored.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.pandas_udf(scored, "double")(text_of()).alias("score"))
    return rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def clean_only(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """The documents of docs that the model does not reject; columns as in docs. Each row is judged alone, null as empty; repeated rows stay or go together."""

    def clean(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series(model.scores(batch) < threshold)

    clean.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return docs.filter(F.pandas_udf(clean, "boolean")(text_of()))
