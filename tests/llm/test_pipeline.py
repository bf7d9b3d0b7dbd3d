"""The pipeline's stages against what each should do to its input."""

import random

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from voxtable.llm import decontaminate, hilbert_shards, mix_sources, simhash_dedup, toxicity


def test_stages_by_brute_force(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    now = [r.asDict() for r in docs.collect()]
    model = toxicity.fit_on(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    now = [r for r, s in zip(now, model.scores([r["text"] for r in now]), strict=True) if s < 0.7]
    sets = {r["doc_id"]: simhash_dedup.shingle_set(r["text"] or "") for r in now}
    sets = {d: set(s.tolist()) for d, s in sets.items()}
    near = {a: [b for b in sets if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])] for a in sets}
    best = {d: d for d in sets}
    for _ in range(len(sets)):
        before = dict(best)
        best = {a: min(before[b] for b in near[a]) for a in sets}
        if best == before:
            break
    now = [r for r in now if best[r["doc_id"]] == r["doc_id"]]
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()
    matcher = decontaminate.Matcher([(r["item_id"], r["text"]) for r in items])
    now = [r for r in now if not matcher.matches(r["text"])]
    mixed = mix_sources.mix_table(spark.createDataFrame(now, docs.schema)).collect()
    copies = {r["doc_id"]: r["copies"] for r in mixed}
    got = {r["doc_id"]: r["n"] for r in corpus_pipeline.run(spark, sf_dir).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert got == {d: n for d, n in copies.items() if n}


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages_take_empty_tables_and_keep_columns(spark, sf_dir, name):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = dict(corpus_pipeline.STAGES)[name](spark, docs.limit(0), sf_dir)
    assert out.count() == 0
    if name != corpus_pipeline.STAGES[-1][0]:
        assert out.columns == docs.columns
    else:
        assert "shard" in out.columns and hilbert_shards.SHARDS == 16


def test_near_copies_by_five_word_similarity(spark):
    rnd = random.Random(8)
    words = ["".join(rnd.choice("abcdefgh") for _ in range(5)) for _ in range(300)]
    passage = " ".join(rnd.choice(words) for _ in range(30))
    texts = [" ".join([*(rnd.choice(words) for _ in range(150)), passage]) for _ in range(90)]
    for i in range(60):
        w = texts[i % 20].split()
        for _ in range(i // 20 * 2 + 1):
            w[rnd.randrange(180)] = rnd.choice(words)
        texts.append(" ".join(w))
    texts += ["", " \n", None, "one two", "One  two", "three"]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in ((t or "").lower().split() for t in texts)]
    best = list(range(len(texts)))
    for _ in texts:
        before = list(best)
        best = [min(best[j] for j in range(len(sets)) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])) for i in range(len(sets))]
        if best == before:
            break
    docs = spark.createDataFrame([(i, t, None, None, 0) for i, t in enumerate(texts)], "doc_id bigint, text string, lang string, source string, n_chars int")
    kept = {r["doc_id"] for r in corpus_pipeline.near_dedup_stage(spark, docs, "").collect()}
    assert kept == set(best) and 90 <= len(kept) < len(texts) - 40


def test_a_common_passage_lists_no_pairs(spark, monkeypatch):
    """200 texts that have half of their shingles in common make hardly any pairs; the near copies among them are found; a group of near copies merges under its centre."""
    rnd = random.Random(9)
    word = lambda: "".join(rnd.choice("abcdefghij") for _ in range(6))
    passage = " ".join(word() for _ in range(60))
    texts = [" ".join([*(word() for _ in range(50)), passage]) for _ in range(200)]
    texts += [t.replace(t.split()[20], "other") for t in texts[:10]]
    centre = [word() for _ in range(120)]
    texts += [" ".join(centre)] + [" ".join(word() if i in changed else w for i, w in enumerate(centre)) for changed in (rnd.sample(range(120), 1 + n % 6) for n in range(90))]
    compared = []
    connected = simhash_dedup.connected

    def counted(met, linked, *args, **named):
        def link(pairs):
            compared.append(pairs.count())
            return linked(pairs)

        return connected(met, link, *args, **named)

    monkeypatch.setattr(simhash_dedup, "connected", counted)
    sets = [{tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in map(str.split, texts)]
    best = list(range(len(texts)))
    near = [[j for j, y in enumerate(sets) if len(x & y) >= 0.8 * len(x | y)] for x in sets]
    for _ in texts:
        best = [min(best[j] for j in near[i]) for i in range(len(sets))]
    docs = spark.createDataFrame([(i, t, None, None, 0) for i, t in enumerate(texts)], "doc_id bigint, text string, lang string, source string, n_chars int")
    assert {r["doc_id"] for r in simhash_dedup.drop_similar(docs).collect()} == set(best)
    assert 0 < sum(compared) < 1000
