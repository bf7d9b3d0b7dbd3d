"""SimHash near-duplicates by a byte-position inverted index with count filtering.

A 64-bit fingerprint is eight positional bytes. Fingerprints that differ in at most three bits differ in at most
three bytes, so they share at least MATCHES = 5 positional bytes: candidates are tallied by shared
positional bytes, those with fewer than MATCHES go, the rest are verified by their differing bits.

Posting lists of single bytes hold a 256th of all fingerprints each, and their pairs grow with the square of the
input. Of five shared positions at least three lie in one half of the fingerprint, so posting lists
are kept for the eight byte triples within a half (24 bits) instead, with no loss. A posting list is walked once in
sorted order, and only a spanning forest of its verified links leaves it: at most one edge for each fingerprint, however
dense a group of near copies is. Lists of over HEAVY fingerprints are dealt out anew by all five shared bytes
(ten lists of 40 bits each); those hold at most 2**24 fingerprints by construction, and neighbours are then looked up by
flipping bits rather than compared, so work stays linear in the list.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, BooleanType, LongType, StructField, StructType

from voxtable.llm.common import broadcast_if_small, columns_of, cut, release, text_of
from voxtable.llm.components import component_roots
from voxtable.llm.lanes import SMALL, connected, shared_lists

SHINGLE = 3
SEED = 42
DISTANCE = 3
MATCHES = 8 - DISTANCE
HEAVY = 16_384
SLICE = 65_536  # words hashed at once


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """Unsigned 64-bit SimHash of the word shingles of a text (A-Z lower-cased, ASCII white space splits)."""
    from xxhash import xxh64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    tally = np.zeros(64, dtype=np.int64)
    for at in range(0, n, SLICE):
        part = words[at : min(at + SLICE, n) + shingle - 1]
        grams = zip(*(part[i:] for i in range(shingle)), strict=False) if len(words) >= shingle else [part]
        h = np.fromiter((xxh64_intdigest(g, SEED) for g in map(b" ".join, grams)), dtype="<u8")
        tally += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    bits = np.packbits(2 * tally > n, bitorder="little")
    return int(bits.view("<u8")[0])


@F.pandas_udf(LongType())
def _fingerprints(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for batch in texts:
        yield pd.Series(np.array([fingerprint(t) for t in batch], dtype=np.uint64).view(np.int64))


def with_fingerprint(docs: DataFrame) -> DataFrame:
    """doc_id, fp (signed long) for each row; null counts as empty."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), _fingerprints(text_of()).alias("fp"))


def _byte(fp: Column, i: int) -> Column:
    return F.shiftrightunsigned(fp, 8 * i).bitwiseAND(F.lit(255).cast("long"))


def _packed(fp: Column, places: tuple[int, ...], name: int) -> Column:
    """The bytes at these positions, and the name of the list kind above them."""
    key = F.lit(name).cast("long")
    for i in places:
        key = F.shiftleft(key, 8).bitwiseOR(_byte(fp, i))
    return key


#: Byte triples within a half; and for each five positions.
TRIPLES = [t for half in ((0, 1, 2, 3), (4, 5, 6, 7)) for t in combinations(half, 3)]
FIVES = list(combinations(range(8), MATCHES))


def _forest(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest of the links among sorted distinct fingerprints v: breadth first, each found once."""
    left = v.copy()
    froms, tos = [], []
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop()
            x = left ^ at
            shared = (x.view(np.uint8).reshape(-1, 8) == 0).sum(axis=1)
            near = shared >= MATCHES
            near[near] = np.bitwise_count(x[near]) <= DISTANCE
            found = left[near]
            if len(found):
                left = left[~near]
                froms.append(np.full(len(found), at, dtype=np.uint64))
                tos.append(found)
                queue.extend(found)
    none = np.empty(0, dtype=np.uint64)
    return (np.concatenate(froms), np.concatenate(tos)) if froms else (none, none)


def _flips(places: list[int]) -> np.ndarray:
    bits = [np.uint64(1) << np.uint64(8 * p + b) for p in places for b in range(8)]
    return np.array([np.bitwise_or.reduce(np.array(c, dtype=np.uint64)) for n in range(1, DISTANCE + 1) for c in combinations(bits, n)], dtype=np.uint64)


def _forest_by_flips(v: np.ndarray, free: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """The same for long lists whose members differ in the free bytes only."""
    flips = _flips(free)
    open_ = np.ones(len(v), dtype=bool)
    froms, tos = [], []
    for root in range(len(v)):
        if not open_[root]:
            continue
        open_[root] = False
        queue = [root]
        while queue:
            at = v[queue.pop()]
            near = at ^ flips
            where = np.minimum(np.searchsorted(v, near), len(v) - 1)
            where = np.unique(where[(v[where] == near) & open_[where]])
            if len(where):
                open_[where] = False
                froms.append(np.full(len(where), at, dtype=np.uint64))
                tos.append(v[where])
                queue.extend(where)
    none = np.empty(0, dtype=np.uint64)
    return (np.concatenate(froms), np.concatenate(tos)) if froms else (none, none)


def _walk(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Rows sorted by (key, fp): list after list, whole lists only; the last of a batch waits for the next batch."""

    def links(keys: np.ndarray, fps: np.ndarray) -> pd.DataFrame:
        starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.empty(0, dtype=np.int64)
        sizes = np.diff(np.r_[starts, len(keys)])
        two = starts[sizes == 2]
        x = fps[two] ^ fps[two + 1]
        tally = (x.view(np.uint8).reshape(-1, 8) == 0).sum(axis=1)
        two = two[(tally >= MATCHES) & (np.bitwise_count(x) <= DISTANCE)]
        froms, tos = [fps[two]], [fps[two + 1]]
        for s, n in zip(starts[sizes > 2], sizes[sizes > 2], strict=True):
            v = np.unique(fps[s : s + n])
            if n > HEAVY:
                five = FIVES[int(keys[s]) >> 40]
                f, t = _forest_by_flips(v, [i for i in range(8) if i not in five])
            else:
                f, t = _forest(v)
            froms.append(f)
            tos.append(t)
        return pd.DataFrame({"a": np.concatenate(froms).view(np.int64), "b": np.concatenate(tos).view(np.int64)})

    held: list[tuple[np.ndarray, np.ndarray]] = []  # pieces of the list that is not over yet
    for batch in batches:
        keys = batch["key"].to_numpy(dtype=np.int64)
        fps = batch["fp"].to_numpy(dtype=np.int64).view(np.uint64)
        if not len(keys):
            continue
        if held and held[0][0][0] == keys[-1]:
            held.append((keys, fps))
            continue
        end = int(np.searchsorted(keys, keys[-1]))
        whole = [*held, (keys[:end], fps[:end])]
        yield links(np.concatenate([k for k, _ in whole]), np.concatenate([f for _, f in whole]))
        held = [(keys[end:], fps[end:])]
    if held:
        yield links(np.concatenate([k for k, _ in held]), np.concatenate([f for _, f in held]))


def fingerprint_links(fps: DataFrame, heavy: int = HEAVY) -> DataFrame:
    """Distinct fp -> edges (a, b) that connect what the links connect."""
    listed = fps.select("fp", F.explode(F.array(*[_packed(F.col("fp"), t, n) for n, t in enumerate(TRIPLES)])).alias("key"))
    long_lists = cut(listed.groupBy("key").count().filter(F.col("count") > heavy).select("key"))
    walk = lambda rows: rows.repartition("key").sortWithinPartitions("key", "fp").mapInPandas(_walk, "a long, b long")
    if long_lists.isEmpty():
        return walk(listed)
    long_lists = broadcast_if_small(long_lists, 100_000)
    short = walk(listed.join(long_lists, "key", "left_anti"))
    again = listed.join(long_lists, "key", "left_semi").select("fp").distinct()
    again = again.select("fp", F.explode(F.array(*[_packed(F.col("fp"), t, n) for n, t in enumerate(FIVES)])).alias("key"))
    return short.unionAll(walk(again))


def simhash_components(docs: DataFrame) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable) for every row.

    Null, empty and blank texts have fingerprint zero and are linked like any other. Rows that repeat a doc_id
    each get a row; a null doc_id is never the smallest while another is there. An empty table gives an
    empty result. Copies collapse to one fingerprint before any pair is made.
    """
    rows = cut(with_fingerprint(docs))
    fps = cut(rows.groupBy("fp").agg(F.min("doc_id").alias("first")))
    roots = component_roots(fingerprint_links(fps.select("fp")))
    placed = fps.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    ids = placed.groupBy("root").agg(F.min("first").alias("component_id"))
    named = placed.join(ids, "root").select("fp", "component_id")
    return rows.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def drop_near_copies(docs: DataFrame) -> DataFrame:
    """The documents of docs that stay: of each group the one with the smallest doc_id; columns as in docs.

    Rows that repeat a doc_id are one document and stay or go together; rows without a doc_id stay.
    """
    dropped = cut(simhash_components(docs).filter("doc_id <> component_id").select("doc_id").distinct())
    return docs.join(broadcast_if_small(dropped, 1_000_000), "doc_id", "left_anti").select(*columns_of(docs))


STAGE_SHINGLE = 5
JACCARD = 0.8
TEXTS = 2_000  # shingle sets held while pairs are verified
PARITIES = 1 << 18  # places for the parities of a set at most


def shingle_set(text: str, shingle: int = STAGE_SHINGLE) -> np.ndarray:
    """Sorted distinct XXH64 of the word shingles of a text; a shorter text is one shingle, a blank one none."""
    from xxhash import xxh64_intdigest

    words = text.encode("utf-8", "surrogatepass").lower().split()
    k = min(shingle, len(words))
    grams = map(b" ".join, zip(*(words[i:] for i in range(k)), strict=False))
    return np.unique(np.fromiter((xxh64_intdigest(g, SEED) for g in grams), dtype=np.uint64))


def _tally(shingles: np.ndarray, starts: np.ndarray) -> np.ndarray:
    bits = np.unpackbits(shingles.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.add.reduceat(bits, starts, axis=0, dtype=np.int64)


def set_simhash(shingles: np.ndarray) -> int:
    """Unsigned SimHash of a set: the bits that more than half of it have; an empty one gives zero."""
    tally = sum((_tally(shingles[at : at + SLICE], np.zeros(1, dtype=np.int64))[0] for at in range(0, len(shingles), SLICE)), np.zeros(64, dtype=np.int64))
    return int(np.packbits(2 * tally > len(shingles), bitorder="little").view("<u8")[0])


def _apart(n: Column) -> Column:
    """Shingles of a set of n that a similar set may lack at most."""
    return F.floor(n / 5)


def _agreeing(n: Column) -> Column:
    """Positions of a set of n that those of any similar set hold too, at least."""
    return F.greatest(F.lit(1), F.floor(F.ceil(4 * n / 5) / 10))


def positions(shingles: np.ndarray) -> np.ndarray:
    """The smallest hashes of a set of n, n / 5 and n / 10 of them: similar sets that are not equal have a tenth of the smaller one in common, and one at least.

    Similar sets have 4 / 5 of the larger one in common. In any order, leave out all of those but the first k: of n shingles at most n / 5 + k are up to there.
    """
    n = len(shingles)
    return shingles[: min(n, n // 5 + max(1, n // 10))]


def parities(shingles: np.ndarray) -> bytes:
    """Shingles are dealt to at least twice as many places as there are (up to PARITIES), a power of two; a bit for each place that got an odd number."""
    count = min(PARITIES, max(64, 1 << (2 * len(shingles) - 1).bit_length()))
    dealt = np.bincount((shingles >> np.uint64(7) & np.uint64(count - 1)).astype(np.int64), minlength=count)
    return np.packbits(dealt & 1, bitorder="little").tobytes()


def may_be_similar(x: bytes, n: int, y: bytes, m: int) -> bool:
    """False only where sets of n and m shingles with these parities differ in more than (n + m) / 9 shingles, hence are less similar than JACCARD.

    Places whose parities differ got a shingle that only one of the sets has. The longer row of parities is folded to the length of the other.
    """
    p, q = np.frombuffer(x, dtype=np.uint64), np.frombuffer(y, dtype=np.uint64)
    if len(p) < len(q):
        p, q = q, p
    while len(p) > len(q):
        p = p[: len(p) // 2] ^ p[len(p) // 2 :]
    return 9 * int(np.bitwise_count(p ^ q).sum(dtype=np.int64)) <= n + m


_SKETCH = [("k1", LongType()), ("k2", LongType()), ("fp", LongType()), ("n", LongType()), ("parities", BinaryType())]
_FOLDED = [f"p{i}" for i in range(4)]  # parities of 256 places


@F.pandas_udf(StructType([StructField(c, t) for c, t in _SKETCH]))
def _sketches(texts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
    from xxhash import xxh3_128_digest

    for batch in texts:
        rows = []
        for text in batch:
            s = shingle_set(text)
            k1, k2 = np.frombuffer(xxh3_128_digest(s.tobytes()), dtype=np.int64)
            rows.append((k1, k2, np.uint64(set_simhash(s)).astype(np.int64), len(s), parities(s)))
        yield pd.DataFrame(rows, columns=[c for c, _ in _SKETCH])


@F.pandas_udf(ArrayType(LongType()))
def _positions(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for batch in texts:
        yield pd.Series([positions(shingle_set(t)).view(np.int64) for t in batch])


@F.pandas_udf(ArrayType(LongType()))
def _shingles(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
    for batch in texts:
        yield pd.Series([shingle_set(t).view(np.int64) for t in batch])


def folded(shingles: np.ndarray) -> np.ndarray:
    """Parities of a set in 256 places, as four longs."""
    dealt = np.bincount((shingles >> np.uint64(40) & np.uint64(255)).astype(np.int64), minlength=256)
    return np.packbits(dealt & 1, bitorder="little").view(np.int64)


@F.pandas_udf(StructType([StructField(c, LongType()) for c in _FOLDED]))
def _folded(texts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
    for batch in texts:
        yield pd.DataFrame(np.array([folded(shingle_set(t)) for t in batch], dtype=np.int64).reshape(-1, 4), columns=_FOLDED)


def similar_lists(once: DataFrame) -> DataFrame:
    """once (id, n, text) of different sets -> key, id, n, rank, alone (shingles that no other has) and folded parities: lists such that two similar sets meet in one where may_meet holds.

    First a part of each set's shingles is listed, by hash alone, and sets of which too few are in another's part go: they have no similar one. Of the
    others all shingles are counted and put in order, rare ones first. The first n / 5 and one more of them hold the first that a set shares
    with a similar one; what no other set holds comes first and is in no list. So a passage of many texts lists none that has enough of its own besides.
    """
    whole, own = Window.partitionBy("key"), Window.partitionBy("id")
    some = once.select("id", F.explode(_positions("text")).alias("key"))
    met = some.withColumns({"low": F.min("id").over(whole), "high": F.max("id").over(whole)}).filter("low < high")
    held = cut(met.groupBy("id").agg(F.count(F.lit(1)).alias("held")))
    alive = cut(held.join(once.select("id", "n"), "id").filter(F.col("held") >= _agreeing(F.col("n"))).select("id"))
    release(once.sparkSession)  # the shuffle of all positions
    left = once.join(broadcast_if_small(alive, 1_000_000), "id")
    parity = cut(left.select("id", _folded("text").alias("p")).select("id", "p.*"))
    rows = left.select("id", "n", F.explode(_shingles("text")).alias("key")).withColumn("holders", F.count(F.lit(1)).over(whole)).filter("holders > 1")
    rows = rows.withColumns({"alone": F.col("n") - F.count(F.lit(1)).over(own), "at": F.row_number().over(own.orderBy("holders", "key")) - 1})
    rows = rows.withColumn("rank", F.col("alone") + F.col("at")).filter(F.col("rank") <= _apart(F.col("n"))).select("key", "id", "n", "rank", "alone")
    return shared_lists(rows.join(broadcast_if_small(parity, SMALL), "id"))


def may_meet(left: str, right: str) -> Column:
    """What holds of two rows (by their aliases) of the first list in which two similar sets meet.

    Neither set holds what the other has before that place, so their ranks count shingles that only one of them has, (n + m) / 9 at most; parities that differ count such, too.
    """
    both = [[F.col(f"{i}.{c}") for i in (left, right)] for c in ("n", "rank", *_FOLDED)]
    n, rank, parity = both[0], both[1], both[2:]
    apart = sum((F.bit_count(x.bitwiseXOR(y)) for x, y in parity), F.lit(0))
    return (5 * F.least(*n) >= 4 * F.greatest(*n)) & (9 * (rank[0] + rank[1]) <= n[0] + n[1]) & (9 * apart <= n[0] + n[1])


@F.pandas_udf(BooleanType())
def _similar_parities(pairs: Iterator[tuple[pd.Series, pd.Series, pd.Series, pd.Series]]) -> Iterator[pd.Series]:
    for columns in pairs:
        yield pd.Series([may_be_similar(*pair) for pair in zip(*columns, strict=True)], dtype=bool)


@F.pandas_udf(BooleanType())
def _similar_texts(pairs: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
    known: dict[str, np.ndarray] = {}

    def of(text: str) -> np.ndarray:
        if text not in known:
            if len(known) >= TEXTS:
                known.clear()
            known[text] = shingle_set(text)
        return known[text]

    for left, right in pairs:
        out = []
        for x, y in zip(left, right, strict=True):
            a, b = of(x), of(y)
            both = len(np.intersect1d(a, b, assume_unique=True))
            out.append(both >= JACCARD * (len(a) + len(b) - both))
        yield pd.Series(out, dtype=bool)


def similar_groups(docs: DataFrame) -> DataFrame:
    """all (the row of docs, as a struct), doc_id, at (a number for the row), kept: links are five-word shingle sets of Jaccard similarity 0.8 or more.

    The SimHash of each set goes through the inverted index of positional bytes, the tally and the check of differing bits as in fingerprint_links. Those links cannot see all
    of similarity 0.8, so sets are listed by their rarest shingles too, as many as similar sets may differ in and one more:
    by the pigeonhole principle no link is without a list in common. All pairs are verified on whole shingle sets. Texts of equal sets collapse first;
    shorter texts are one shingle; null, empty and blank texts are equal. Each group keeps its row of the smallest doc_id (null last, then the
    first row); texts may have any length, rows may repeat.
    """
    rows = docs.select(F.struct(*columns_of(docs)).alias("all"), F.col("doc_id").cast("long").alias("doc_id"), text_of().alias("text"), F.monotonically_increasing_id().alias("at"))
    rows = cut(rows.select("all", "doc_id", "at", _sketches("text").alias("s")).select("all", "doc_id", "at", "s.*"))
    texts = rows.select(F.col("at").alias("id"), F.coalesce(F.col("all.text").cast("string"), F.lit("")).alias("text"))
    sets = cut(rows.groupBy("k1", "k2").agg(F.min("at").alias("id"), F.first("fp").alias("fp"), F.count(F.lit(1)).alias("times")))
    named = sets.filter("times > 1").select("k1", "k2", "id")
    copies = cut(rows.select("at", "k1", "k2").join(broadcast_if_small(named, SMALL), ["k1", "k2"]).filter("at <> id").select(F.col("at").alias("id"), F.col("id").alias("first")))

    fps = cut(sets.groupBy("fp").agg(F.min("id").alias("first")))
    a, b = (fps.select(F.col("fp").alias(i), F.col("first").alias(f"first_{i}")) for i in "ab")
    seeds = fingerprint_links(fps.select("fp")).join(a, "a").join(b, "b").select(F.col("first_a").alias("a"), F.col("first_b").alias("b"))
    seeds = seeds.unionAll(sets.join(fps, "fp").filter("id <> first").select(F.col("first").alias("a"), F.col("id").alias("b")))

    once = rows.select(F.col("at").alias("id"), "n", F.coalesce(F.col("all.text").cast("string"), F.lit("")).alias("text"))
    met = similar_lists(once.join(broadcast_if_small(copies.select("id"), 1_000_000), "id", "left_anti"))
    deals = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    sketches = rows.select(F.col("at").alias("id"), "n", "parities")

    def with_both(pairs: DataFrame, of: DataFrame) -> DataFrame:
        wanted = cut(pairs.select(F.col("a").alias("id")).unionAll(pairs.select("b")).distinct())
        some = of.join(broadcast_if_small(wanted, 1_000_000), "id")
        a, b = (some.select(F.col("id").alias(i), *[F.col(c).alias(f"{c}_{i}") for c in of.columns if c != "id"]) for i in "ab")
        return pairs.repartition(deals, "a").join(a, "a").repartition(deals, "b").join(b, "b")

    def similar(pairs: DataFrame) -> DataFrame:
        # most pairs that meet are none by their parities, a fiftieth of their texts
        near = with_both(pairs, sketches).filter(5 * F.least("n_a", "n_b") >= 4 * F.greatest("n_a", "n_b"))
        near = cut(near.select("a", "b", _similar_parities("parities_a", "n_a", "parities_b", "n_b").alias("near")).filter("near").select("a", "b"))
        links = with_both(near, texts).select("a", "b", _similar_texts("text_a", "text_b").alias("link"))
        return cut(links.filter("link").select("a", "b"))

    roots = connected(met, similar, may_meet, seeds, best="alone")
    # of copies and sets that are linked: the group of each row; rows alone in theirs stay
    grouped = roots.unionAll(copies.join(broadcast_if_small(roots.withColumnRenamed("id", "first"), SMALL), "first", "left").select("id", F.coalesce("root", "first").alias("root")))
    grouped = grouped.unionAll(named.select("id", F.col("id").alias("root")).join(broadcast_if_small(roots.select("id"), SMALL), "id", "left_anti"))
    grouped = grouped.withColumnRenamed("id", "at")
    placed = rows.select("doc_id", "at").join(broadcast_if_small(cut(grouped), SMALL), "at")
    placed = cut(placed.select("at", "root", F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "at").alias("place")))
    first = placed.groupBy("root").agg(F.min("place")["at"].alias("first"))
    gone = cut(placed.join(first, "root").filter("at <> first").select("at"))
    return rows.select("all", "doc_id", "at").join(broadcast_if_small(gone.withColumn("gone", F.lit(True)), 1_000_000), "at", "left").select("all", "doc_id", "at", F.col("gone").isNull().alias("kept"))


def drop_similar(docs: DataFrame) -> DataFrame:
    """The rows of docs that similar_groups keeps; columns as in docs, whatever their names."""
    kept = similar_groups(docs).filter("kept")
    return kept.select(*[F.col("all.`" + c.replace("`", "``") + "`").alias(c) for c in docs.columns])
