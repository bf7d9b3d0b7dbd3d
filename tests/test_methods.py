"""Worked examples, edge cases and invariants of the methods."""

import itertools
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as hs
from pyspark.sql import functions as F

from voxtable.functions.units import char_edits, word_edits
from voxtable.operators import consensus, dist, err, fsq, instruct, judged, lenratio, metrics, mixture, policy, punct, reward, segment, signal, surrogate, textnorm, vq
from voxtable.plans import published
from voxtable.sources.tables import load


def one(spark, *cols):
    return spark.range(1).select(*cols).first()


def arr(*xs):
    return F.array(*[F.lit(x) for x in xs])


# quantiser


def test_codes_of_two_digits_invert(spark):
    rows = spark.createDataFrame([([a, b],) for a, b in itertools.product((-1, 0, 1), repeat=2)], "d array<int>")
    out = rows.select("d", fsq.encode(F.col("d"), 1).alias("s"), fsq.encode(F.col("d"), 1, "printed").alias("p")).withColumn("back", fsq.decode(F.col("s"), 2, 1)).withColumn("back_p", fsq.decode(F.col("p"), 2, 1, "printed")).collect()
    assert sorted(r["s"] for r in out) == list(range(9))
    assert sorted(r["p"] for r in out) == list(range(-4, 5))
    assert all(r["d"] == r["back"] == r["back_p"] for r in out)


def test_halves_go_away_from_zero_and_are_bounded(spark):
    assert one(spark, fsq.bounded_round(arr(-1.5, -0.5, 0.5, 1.5, 9.0), 1).alias("d"))["d"] == [-1, -1, 1, 1, 1]
    assert one(spark, fsq.bounded_round(arr(-1.5, -0.5, 0.5, 1.5, 9.0), 4).alias("d"))["d"] == [-2, -1, 1, 2, 4]
    assert one(spark, fsq.bounded_round(arr(0.0), 3, "tanh").alias("d"))["d"] == [0]


def test_codebook_sizes():
    spec = fsq.FsqSpec(digits=6, k=1)
    assert spec.codebook_size == 729 and spec.codebook_size_as_printed == 243


def test_straight_through_stops_outside_the_bound(spark):
    assert one(spark, fsq.ste_grad(arr(1.0, 2.0), arr(0.5, 9.0), 4).alias("g"))["g"] == [1.0, 0.0]


def test_nearest_entry_matches_brute_force(spark, sf_dir):
    from voxtable.plans.speech_tokens import BOOK

    rows = vq.assign(load(spark, sf_dir, "embeddings"), BOOK).limit(50).collect()
    for r in rows:
        d = ((np.array(BOOK) - np.array(r["embedding"], dtype=float)) ** 2).sum(axis=1)
        assert r["code"] == int(d.argmin())


# edit distances


@pytest.mark.parametrize(("ref", "hyp", "edits"), [("", "", 0), ("", "a b", 2), ("a b", "", 2), ("a b c", "a b c", 0), ("a b c", "a x c", 1), ("a b c", "a c", 1), ("a b", "a x b", 1), ("a a a", "a", 2), ("é ñ", "é n", 1)])
def test_word_edits(spark, ref, hyp, edits):
    assert one(spark, word_edits(F.lit(ref), F.lit(hyp)).alias("e"))["e"] == edits


def test_characters_are_code_points(spark):
    assert one(spark, char_edits(F.lit("かな漢字"), F.lit("かな漢")).alias("e"))["e"] == 1


@settings(max_examples=25, deadline=None)
@given(hs.lists(hs.sampled_from("abc"), max_size=7), hs.lists(hs.sampled_from("abc"), max_size=7))
def test_alignment_counts_add_up_to_the_distance(ref, hyp):
    s, d, i = err._counts(ref, hyp)
    prev = list(range(len(hyp) + 1))
    for k, a in enumerate(ref):
        cur = [k + 1]
        for j, b in enumerate(hyp):
            cur.append(min(prev[j] + (a != b), prev[j + 1] + 1, cur[-1] + 1))
        prev = cur
    assert s + d + i == prev[-1] and i - d == len(hyp) - len(ref)


def test_corruption_makes_no_more_edits_than_drawn(spark, sf_dir):
    rows = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("utt_id"), "text")
    clean = err.scored(surrogate.transcripts(rows, ["human"]), F.lit("word"))
    assert clean.agg(F.sum("edits")).first()[0] == 0


# consensus


def _said(spark, *texts):
    return spark.createDataFrame([(1, f"asr_{i}", t) for i, t in enumerate(texts)], "utt_id bigint, system string, hyp string")


def test_agreement_bound_is_strict(spark):
    twenty = " ".join(f"w{i}" for i in range(20))
    other = twenty.replace("w0 ", "x ").replace("w1 ", "y ").replace("w2 ", "z ")  # three of twenty: 0.15
    assert consensus.select(_said(spark, twenty, other)).count() == 0
    assert consensus.select(_said(spark, twenty, twenty)).count() == 2
    nearer = twenty.replace("w0 ", "x ").replace("w1 ", "y ")
    assert consensus.select(_said(spark, twenty, nearer)).count() == 2


def test_picks(spark):
    rows = _said(spark, "a b c d e f g h i x", "a b c d e f g h i j", "a b c d e f g h i j")
    assert consensus.select(rows, pick="medoid").first()["system"] == "asr_1"
    assert consensus.select(rows, pick="priority").first()["system"] == "asr_0"


# punctuation and volume


@pytest.mark.parametrize(("punct_", "gap", "out"), [("", 299, "w"), ("", 300, "w,"), ("", 301, "w,"), (".", 300, "w."), (",", 49, "w"), ("!", 50, "w"), ("?", 51, "w?"), (";", None, "w;"), ("", None, "w"), (":", 50, "w"), ("", 50, "w")])
def test_pause_bounds(spark, punct_, gap, out):
    word = F.struct(F.lit("w").alias("word"), F.lit(punct_).alias("punct"), F.lit(gap).cast("int").alias("gap_ms"))
    assert one(spark, punct.adjusted(F.array(word)).alias("t"))["t"] == out


def test_volume_edges(spark):
    rows = spark.createDataFrame([([0.0, 0.0],), ([-1.0, -2.0],), ([1.0, 2.0],), ([3.0],)], "samples array<double>")
    out = signal.normalize_volume(rows).collect()
    assert [r["vol_degenerate"] for r in out] == [True, True, False, False]
    assert out[0]["samples"] == [0.0, 0.0] and out[1]["samples"] == [-1.0, -2.0]
    assert max(out[2]["samples"]) == pytest.approx(0.6) and out[3]["samples"] == pytest.approx([0.6])
    assert signal.normalize_volume(rows, "absmax").collect()[1]["samples"] == pytest.approx([-0.3, -0.6])


# length ratios


@pytest.mark.parametrize("n", [1, 10, 100, 101])
def test_rank_mode_cuts_floors(spark, n):
    rows = spark.range(n).select(F.col("id").alias("utt_id"), (F.col("id") % 7).cast("double").alias("ratio"))
    kept = lenratio.trim(rows)
    assert kept.count() == n - math.floor(0.01 * n) - math.floor(0.05 * n)
    expect = sorted(((i % 7, i) for i in range(n)))[math.floor(0.01 * n) : n - math.floor(0.05 * n)]
    assert sorted((r["ratio"], r["utt_id"]) for r in kept.collect()) == expect


def test_ratio_without_text_is_rejected(spark):
    rows = spark.createDataFrame([(1, 10, 0), (2, 10, 5)], "utt_id bigint, n_speech_tok bigint, n_text_tok bigint")
    assert [r["utt_id"] for r in lenratio.trim(lenratio.with_ratio(rows)).collect()] == [2]


def test_sketch_keeps_about_as_many(spark):
    rows = spark.range(5000).select(F.col("id").alias("utt_id"), ((F.col("id") * 7919) % 5000).cast("double").alias("ratio"))
    assert abs(lenratio.trim(rows, method="sketch").count() - 4700) <= 5


# segments


def test_grid_and_greedy_caps(spark):
    sec = segment.SECOND
    rows = spark.createDataFrame([(1, i, int(t * sec), "a", 1.0) for i, t in enumerate((0, 4, 8, 12, 16, 20, 24, 28, 29.96, 30.0, 30.04, 34))], "rec_id bigint, frame bigint, us bigint, kind string, amp double")
    framed = segment.with_segments(rows)
    for cap in ("grid", "greedy"):
        pieces = segment.summarise(segment.cap_duration(framed, cap=cap), "rec_id", "seg_id", "piece").collect()
        assert all(p["dur_s"] < 30 for p in pieces) and sum(p["n_frames"] for p in pieces) == 12 and len(pieces) == 2


# distributions and rewards


def test_divergence(spark):
    assert one(spark, dist.token_kl(arr(0.25, 0.75), arr(0.25, 0.75)).alias("k"))["k"] == 0
    assert one(spark, dist.token_kl(arr(1.0, 0.0, 0.0, 0.0), arr(0.25, 0.25, 0.25, 0.25)).alias("k"))["k"] == pytest.approx(math.log(4))
    assert sum(one(spark, dist.softmax(arr(1.0, 2.0, 900.0)).alias("p"))["p"]) == pytest.approx(1)


def test_cold_samples_are_one_hot(spark):
    w = one(spark, dist.gumbel_softmax(arr(0.0, 1.0, 0.5), arr(0.1, 0.2, 0.0), 0.01).alias("w"))["w"]
    assert max(w) == pytest.approx(1) and one(spark, dist.gumbel_softmax(arr(0.0, 1.0, 0.5), arr(0.1, 0.2, 0.0), 0.01, "hard").alias("w"))["w"] == [0.0, 1.0, 0.0]


def test_noise_picks_codes_as_softmax_says(spark):
    noise = F.array(*[dist.gumbel("t", F.col("id"), F.lit(k)) for k in range(3)])
    hits = spark.range(6000).select(F.array_position(dist.gumbel_softmax(arr(0.0, 1.0, 2.0), noise, 1.0, "hard"), F.lit(1.0)).alias("k")).groupBy("k").count().collect()
    p = np.exp([0, 1, 2]) / np.exp([0, 1, 2]).sum()
    for r in hits:
        assert abs(r["count"] / 6000 - p[r["k"] - 1]) < 0.03


def test_gradient_by_finite_differences():
    rng = np.random.default_rng(1)
    theta, ref, values, noise = rng.normal(size=4), rng.normal(size=4), rng.normal(size=4), rng.gumbel(size=(8, 4))
    cfg = reward.Settings(beta=0.3, tau=0.7)

    def f(t):
        _, r, kl = reward.gradient(t, ref, values, noise, cfg)
        return r - cfg.beta * kl

    g, _, _ = reward.gradient(theta, ref, values, noise, cfg)
    for k in range(4):
        e = np.eye(4)[k] * 1e-6
        assert g[k] == pytest.approx((f(theta + e) - f(theta - e)) / 2e-6, abs=1e-5)


def test_optimiser_raises_the_objective_and_divergence_holds_it_back(spark, sf_dir):
    from voxtable.plans.rewards import start

    _, free = reward.optimize(start(spark, sf_dir), reward.Settings(iters=8, beta=0.0))
    _, held = reward.optimize(start(spark, sf_dir), reward.Settings(iters=8, beta=5.0))
    assert free[-1]["reward"] > free[0]["reward"] and 0 <= held[-1]["kl"] < free[-1]["kl"]


def test_two_codes_reach_the_closed_form():
    cfg = reward.Settings(beta=1.0)
    theta, ref, values = np.zeros(2), np.array([0.2, -0.1]), np.array([1.0, 0.0])
    for _ in range(4000):  # the exact gradient of expected reward in place of sampled noise
        p = np.exp(theta) / np.exp(theta).sum()
        q = np.exp(ref) / np.exp(ref).sum()
        ratio = np.log(p / q)
        theta = theta + 0.1 * (p * (values - p @ values) - cfg.beta * p * (ratio - p @ ratio))
    q = np.exp(ref) * np.exp(values / cfg.beta)
    assert np.exp(theta) / np.exp(theta).sum() == pytest.approx(q / q.sum(), abs=1e-6)


def test_policy_sums_to_one(spark, sf_dir):
    from voxtable.plans.rewards import logits

    for r in logits(spark, sf_dir).collect():
        assert sum(map(math.exp, r["logits"])) == pytest.approx(1)
    assert policy.dense is not None


# text


def test_tags(spark):
    text = F.lit("a [laughter] <strong>b c</strong> <strong>d</strong> [breath] e")
    r = one(spark, instruct.bursts(text).alias("b"), instruct.emphasis(text).alias("e"), instruct.well_formed(text).alias("ok"), instruct.strip_tags(text).alias("t"))
    assert (r["b"], r["e"], r["ok"], r["t"]) == (["laughter", "breath"], ["b c", "d"], True, "a b c d e")
    for bad in ("<strong>a", "<strong>a <strong>b</strong></strong>", "a</strong>"):
        assert not one(spark, instruct.well_formed(F.lit(bad)).alias("ok"))["ok"]


def test_prompts_leave_blanks(spark):
    null = F.lit(None).cast("string")
    say = lambda s, t: one(spark, instruct.speaker_style_prompt(s, t).alias("p"))["p"]
    assert say(F.lit("A"), F.lit("happy")) == "Speaker A. Style: happy."
    assert say(null, F.lit("happy")) == "Style: happy." and say(F.lit("A"), null) == "Speaker A." and say(null, null) == ""
    assert one(spark, instruct.with_prompt(F.lit("calm"), F.lit(f"x{instruct.END}y")).alias("p"))["p"] == f"calm{instruct.END}xy"


def test_script_tables(spark):
    assert one(spark, textnorm.fold_script(F.lit("カタカナ"), textnorm.kana_table()).alias("k"))["k"] == "かたかな"
    assert one(spark, textnorm.to_kana(F.lit("日本語の本"), {"日本": "にほん", "日本語": "にほんご", "本": "ほん"}).alias("k"))["k"] == "にほんごのほん"


def test_normalising_and_back(spark):
    r = one(spark, textnorm.normalize(F.lit("a 42% b"), F.lit("en")).alias("s"))["s"]
    assert r == "a four two percent b"
    assert one(spark, textnorm.denormalize(F.lit(r), F.lit("en")).alias("t"))["t"] == "a 4 2 % b"


# measures over printed cells


def test_claims_derived_from_printed_cells(spark):
    cells = published.cells(spark)
    gain = lambda tbl, a, b: {(r["subset"], r["metric"]): round(r["gain"], 1) for r in metrics.relative(cells.filter(F.col("tbl") == tbl), a, b).collect()}
    assert gain("public", "gen2", "new_l+ro")["zh", "cer"] == 51.0 and gain("public", "gen2", "new_l+ro")["en", "wer"] == 43.6
    s = gain("public", "new_s", "new_s+ro")
    assert (s["zh", "cer"], s["en", "wer"], s["hard", "cer"]) == (35.3, 12.9, 16.3)
    assert gain("multilingual", "new_s", "new_s+ro")["ko", "error"] == 68.6
    assert gain("tokenizers", "tok_sup_new_3k", "tok_sup_new_170k")["hard", "cer"] == 74.8
    assert gain("instructed", "gen2", "new_l")["exprset", "similarity"] == 11.9
    w = metrics.wins(cells.filter("tbl = 'cross_lingual'"), "new_l", "new_s").first()
    assert (w["wins"], w["losses"]) == (11, 1)
    over = lambda a, b: metrics.gain_histogram(metrics.relative(cells.filter("tbl = 'cross_lingual'"), a, b)).first()["over_50"]
    assert (over("new_s", "new_s+ro"), over("new_l", "new_l+ro")) == (5, 4)
    assert sum(mixture.TOKENIZER_KHOURS.values()) == 530


def test_unsupported_cells(spark):
    cells = published.cells(spark)
    assert cells.filter("value IS NULL").count() > 0
    filled = metrics.fill_unsupported(cells).filter("model = 'oss_1' AND subset = 'ko'").first()
    assert filled["value"] == 100.0
    assert metrics.podium(cells).filter("value IS NULL AND rank IS NOT NULL").count() == 0


def test_raters_off_the_grid_or_unbalanced_fail(spark):
    rows = spark.createDataFrame([("s", 1, i, "f" if i % 2 else "m", "zh", 4.0) for i in range(10)] + [("s", 2, i, "f", "zh", 4.2) for i in range(10)], "system string, sentence bigint, rater int, gender string, lang string, score double")
    out = {r["sentence"]: r for r in judged.validate(rows).collect()}
    assert out[1]["balanced"] and out[1]["on_grid"] and not out[2]["balanced"] and not out[2]["on_grid"]


# samples and plans


def test_scales_nest(spark):
    rows = mixture.nested_scales(spark.range(3000), {"a": 0.1, "b": 0.5, "c": 1.0}, "id").select("scale", "id").collect()
    ids = {s: {r["id"] for r in rows if r["scale"] == s} for s in "abc"}
    assert ids["a"] < ids["b"] < ids["c"] and len(ids["c"]) == 3000 and abs(len(ids["a"]) - 300) < 80


def test_temperature_weights_flatten():
    w = mixture.temperature_weights({"x": 90.0, "y": 10.0}, 2.0)
    assert 90 * w["x"] + 10 * w["y"] == pytest.approx(100) and w["y"] > 1 > w["x"]


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf_dir):
    from voxtable.plans import corpus, relational, speech_tokens

    scan = _plan(relational.scan_pruned_filter(spark, sf_dir))
    assert "PushedFilters: [IsNotNull(l_quantity)" in scan and "l_shipdate" not in scan.split("ReadSchema")[1].split("\n")[0]
    tokens = _plan(speech_tokens.b5_tokenize(spark, sf_dir))
    assert "Exchange" not in tokens and "Python" not in tokens
    segments = _plan(corpus.a1_segments(spark, sf_dir))
    assert segments.count("Exchange hashpartitioning") == 1
    for build in (corpus.a3_consensus_utt, corpus.a6_rank, corpus.a4_punct):
        plan = _plan(build(spark, sf_dir))
        assert "CartesianProduct" not in plan and "Python" not in plan and "Pandas" not in plan


def test_short_items_leak_too(spark):
    from voxtable.operators import bench_sets

    docs = ["one two", "xone two three four five six seven eight nine", "two one", "a one twofold", None, ""]
    items = ["one two", "two three four", "nine", "one two three four five six seven eight", None]
    train = spark.createDataFrame(list(enumerate(docs)), "doc_id bigint, text string")
    got = bench_sets.leakage(train, spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string"), "doc_id").collect()
    assert sorted(map(tuple, got)) == [(d, i) for d, t in enumerate(docs) for i, x in enumerate(items) if t is not None and x is not None and x in t]
