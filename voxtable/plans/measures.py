"""Queries of the cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.functions.hashing import sql_draw, sql_uniform
from voxtable.functions.units import sql_char_edits, sql_word_edits, sql_words, unit_of, word_edits, words
from voxtable.functions.vectors import cosine
from voxtable.operators import bench_sets, consensus, err, judged, metrics, surrogate
from voxtable.operators.tokens import centroids
from voxtable.plans import published
from voxtable.plans.corpus import sql_corrupt
from voxtable.plans.corpus_sets import EMO, emotions
from voxtable.registry import query
from voxtable.sources.tables import load

ITEMS = "SELECT item_id AS utt_id, text, 'en' AS lang FROM benchmark"
HEARD = sql_corrupt(consensus.RECOGNISERS, ITEMS)
SCORED = f"WITH t AS ({HEARD}), sc AS (SELECT utt_id, system, ref, hyp, {sql_word_edits('ref', 'hyp')} AS edits, len({sql_words('ref')}) AS n_ref FROM t)"
P = f"WITH cells AS ({published.sql()})"


def heard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """utt_id, system, ref, hyp: benchmark items as three recognisers hear them."""
    return consensus.transcribe(load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("utt_id"), "text"))


def _scored(spark: SparkSession, sf_dir: str, unit: str = "word") -> DataFrame:
    return err.scored(heard(spark, sf_dir), F.lit(unit))


def _r(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


@query("i1_cer", f"WITH t AS ({HEARD}) SELECT utt_id, system, {sql_char_edits('ref', 'hyp')}::BIGINT AS edits, length(ref) AS n_ref FROM t")
def i1_cer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _scored(spark, sf_dir, "char").select("utt_id", "system", "edits", "n_ref")


@query("i2_wer", SCORED + " SELECT utt_id, system, edits::BIGINT AS edits, n_ref::BIGINT AS n_ref FROM sc")
def i2_wer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _scored(spark, sf_dir).select("utt_id", "system", "edits", "n_ref")


@query("i3_micro_macro", SCORED + " SELECT system, count(*) AS n, round(sum(edits) / sum(n_ref)::DOUBLE, 6) AS micro, round(avg(edits / n_ref::DOUBLE), 6) AS macro FROM sc GROUP BY system")
def i3_micro_macro(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(err.corpus_rate(_scored(spark, sf_dir), "system"))


@query("i4_align")
def i4_align(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = err.align_counts(_scored(spark, sf_dir))
    return counted.select("utt_id", "system", "sub", "del", "ins", "edits")


@query("i5_bounded", f"WITH t AS ({HEARD}) SELECT utt_id, system, {sql_char_edits('ref', 'hyp')} <= 10 AS within FROM t")
def i5_bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    return heard(spark, sf_dir).select("utt_id", "system", err.within(F.col("ref"), F.col("hyp"), 10).alias("within"))


def _cos(a: str, b: str) -> str:
    dot = lambda x, y: f"list_sum(list_transform(list_zip({x}, {y}), lambda p: p[1]::DOUBLE * p[2]::DOUBLE))"
    return f"{dot(a, b)} / (sqrt({dot(a, a)}) * sqrt({dot(b, b)}))"


PAIRED = "WITH pr AS (SELECT label, vec_id, embedding AS x, lead(embedding) OVER (PARTITION BY label ORDER BY vec_id) AS y FROM embeddings QUALIFY y IS NOT NULL)"


@query("i6_speaker_sim", PAIRED + f" SELECT label, round(avg({_cos('x[1:32]', 'y[1:32]')}), 6) AS a, round(avg({_cos('x[33:64]', 'y[33:64]')}), 6) AS b FROM pr GROUP BY label")
def i6_speaker_sim(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = judged.paired(load(spark, sf_dir, "embeddings"), "label", "vec_id", "embedding")
    one = lambda v: F.avg(cosine(judged.view(F.col("x"), v), judged.view(F.col("y"), v))).alias(v)
    return _r(pairs.groupBy("label").agg(one("a"), one("b")))


@query(
    "i7_style_sim",
    """WITH e AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings), m AS (SELECT label, pos, avg(x) AS m FROM e GROUP BY 1, 2),
    s AS (SELECT vec_id, e.label, sum(x * m) / (sqrt(sum(x * x)) * sqrt(sum(m * m))) AS c FROM e JOIN m ON e.label = m.label AND e.pos = m.pos GROUP BY 1, 2) SELECT label, round(100 * avg(c), 4) AS similarity FROM s GROUP BY label""",
)
def i7_style_sim(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings")
    joined = rows.join(centroids(rows, "label", "embedding"), "label")
    return _r(joined.groupBy("label").agg((100 * F.avg(cosine(F.col("embedding"), F.col("centre")))).alias("similarity")), 4)


@query("i8_quality", "SELECT doc_id, round(least(5.0::DOUBLE, 2.0::DOUBLE + 1.5::DOUBLE * coalesce(quality, 0.5::DOUBLE) + least(1.5::DOUBLE, n_chars / 2000.0::DOUBLE)), 6) AS mos FROM documents LEFT JOIN labels USING (doc_id)")
def i8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "documents").select("doc_id", "n_chars").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.round(judged.mos_pred(F.col("n_chars"), F.col("quality")), 6).alias("mos"))


RATED = "WITH rt AS (SELECT event_type AS system, event_id % 200 AS sentence, (user_id % 10)::INT AS rater, CASE WHEN event_id % 2 = 0 THEN 'zh' ELSE 'en' END AS lang, CASE WHEN user_id % 2 = 0 THEN 'f' ELSE 'm' END AS gender, least(5, 1 + 0.5::DOUBLE * floor(least(value, 200) / 25)) AS score FROM events)"


@query("i9_mos", RATED + " SELECT system, lang, count(*) AS n, round(avg(score), 6) AS mos, round(1.96::DOUBLE * stddev_samp(score) / sqrt(count(*)), 6) AS ci95 FROM rt GROUP BY GROUPING SETS ((system, lang), (system))")
def i9_mos(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(judged.opinion(judged.ratings(load(spark, sf_dir, "events"))))


@query("i9_language_means", RATED + " SELECT system, round(avg(m), 6) AS mos FROM (SELECT system, lang, avg(score) AS m FROM rt GROUP BY 1, 2) GROUP BY system")
def i9_language_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(judged.mean_of_languages(judged.ratings(load(spark, sf_dir, "events"))))


@query("i9_validate", RATED + " SELECT system, sentence, count(*) FILTER (WHERE gender = 'f') AS n_f, count(*) FILTER (WHERE gender = 'm') AS n_m, true AS on_grid, count(*) FILTER (WHERE gender = 'f') = 5 AND count(*) FILTER (WHERE gender = 'm') = 5 AS balanced FROM rt GROUP BY system, sentence")
def i9_validate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged.validate(judged.ratings(load(spark, sf_dir, "events")))


GUESS = f"CASE WHEN {sql_draw(chr(39) + 'guess' + chr(39), 'doc_id')} % 100 < CASE WHEN relation = 'related' THEN 85 ELSE 55 END THEN emotion ELSE CASE {sql_draw(chr(39) + 'wrong' + chr(39), 'doc_id')} % 3 WHEN 0 THEN 'happy' WHEN 1 THEN 'sad' ELSE 'angry' END END"
GUESSED = EMO + f", gs AS (SELECT *, {GUESS} AS pred FROM e)"


def guessed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Emotions with a hashed classifier's answer: right more often where text and emotion are related."""
    right = bench_sets.draw("guess", F.col("doc_id")) % 100 < F.when(F.col("relation") == "related", 85).otherwise(55)
    wrong = F.element_at(F.array(F.lit("happy"), F.lit("sad"), F.lit("angry")), (bench_sets.draw("wrong", F.col("doc_id")) % 3).cast("int") + 1)
    return emotions(spark, sf_dir).withColumn("pred", F.when(right, F.col("emotion")).otherwise(wrong)).withColumn("truth", F.col("emotion"))


@query("i10_emotion", GUESSED + " SELECT relation, emotion, count(*) AS n, round(avg((pred = emotion)::INT), 6) AS accuracy FROM gs GROUP BY relation, emotion")
def i10_emotion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(judged.accuracy(guessed(spark, sf_dir), "relation", "emotion"))


@query("i11_tasks", GUESSED + " SELECT lang AS task, count(*) AS n, round(avg((pred = emotion)::INT), 6) AS accuracy FROM gs GROUP BY lang")
def i11_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(judged.accuracy(guessed(spark, sf_dir).withColumnRenamed("lang", "task"), "task"))


@query("i11_confusion", GUESSED + " SELECT emotion AS truth, count(*) FILTER (WHERE pred = 'angry') AS angry, count(*) FILTER (WHERE pred = 'happy') AS happy, count(*) FILTER (WHERE pred = 'sad') AS sad FROM gs GROUP BY emotion")
def i11_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged.confusion(guessed(spark, sf_dir), ["angry", "happy", "sad"])


@query("i11_macro_f1", GUESSED + ", tp AS (SELECT c, sum(hit)::DOUBLE / sum(n) AS f1 FROM (SELECT emotion AS c, CASE WHEN pred = emotion THEN 1 ELSE 0 END AS hit, 1 AS n FROM gs UNION ALL SELECT pred, CASE WHEN pred = emotion THEN 1 ELSE 0 END, 1 FROM gs) GROUP BY c) SELECT round(avg(f1), 6) AS macro_f1 FROM tp")
def i11_macro_f1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(judged.macro_f1(guessed(spark, sf_dir)))


SYSTEMS = ("nar_3", "ar_4", "gen2", "gen2+ro", "new_s", "new_s+ro", "new_l", "new_l+ro")
CHANCES = ", ".join(f"('{s}', {sum(surrogate.SYSTEMS[s])})" for s in SYSTEMS)
#: Each document as each system says it: whether it fails, null where it does not support the language.
SAID = f"""WITH said AS (SELECT doc_id, lang, source, n_chars, system, CASE WHEN {surrogate.sql_supported('lang', 'system')} THEN {sql_draw("'cell'", 'system', 'doc_id')} % 10000 < chance END AS hit FROM documents, (VALUES {CHANCES}) AS s(system, chance))"""


def said(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars")
    return surrogate.failed(docs, SYSTEMS, "doc_id", "cell")


@query("i12_correction", SAID + " SELECT a.system AS variant, a.lang, sum(a.hit::INT)::BIGINT AS errors, sum((a.hit AND NOT b.hit)::INT)::BIGINT AS corrected, round(100.0::DOUBLE * sum((a.hit AND NOT b.hit)::INT) / nullif(sum(a.hit::INT), 0), 6) AS rate FROM said a JOIN said b ON b.doc_id = a.doc_id AND b.system = a.system || '+ro' WHERE a.hit IS NOT NULL GROUP BY a.system, a.lang")
def i12_correction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that a system fails on, and those of them that its optimised form says right."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang")
    both = surrogate.failed(docs, [s for s in SYSTEMS if f"{s}+ro" in SYSTEMS], "doc_id", "cell", "+ro").filter("hit IS NOT NULL")
    counted = both.select(F.col("system").alias("variant"), "lang", F.col("hit").cast("long").alias("errors"), (F.col("hit") & ~F.col("other")).cast("long").alias("corrected"))
    return _r(judged.correction_rate(counted, "variant", "lang"))


def _relative(base: str, new: str) -> str:
    return f"(SELECT o.tbl, o.subset, o.metric, o.value AS base, n.value AS new, CASE WHEN o.metric IN ('cer', 'wer', 'error') THEN o.value - n.value ELSE n.value - o.value END * 100 / o.value AS gain FROM cells o JOIN cells n ON o.tbl = n.tbl AND o.subset = n.subset AND o.metric = n.metric WHERE o.model = '{base}' AND n.model = '{new}')"


#: The comparison's tables and the column that parts each.
PARTS = {"multilingual": "lang", "public": "source"}
MEASURED = SAID + ", cells AS (" + " UNION ALL ".join(
    f"""SELECT '{t}' AS tbl, system AS model, {c} AS subset, metric, CASE metric WHEN 'error' THEN 100.0::DOUBLE * sum(CASE WHEN hit THEN n_chars ELSE 0 END) FILTER (WHERE hit IS NOT NULL) / nullif(sum(n_chars) FILTER (WHERE hit IS NOT NULL), 0) ELSE 1 - count(*) FILTER (WHERE hit) / nullif(count(hit), 0)::DOUBLE END AS value FROM said, (VALUES ('error'), ('similarity')) AS m(metric) GROUP BY system, {c}, metric"""
    for t, c in PARTS.items()
) + ")"


def measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """tbl, model, subset, metric, value: share of characters in documents that fail (%), and of documents that do not; null where nothing is supported."""
    parts = F.explode(F.array(*[F.struct(F.lit(t).alias("tbl"), F.col(c).alias("subset")) for t, c in PARTS.items()])).alias("p")
    rows = said(spark, sf_dir).select(F.col("system").alias("model"), "n_chars", "hit", parts).select("model", "n_chars", "hit", "p.*")
    chars = lambda when: F.sum(F.when(when, F.col("n_chars")))
    sums = rows.groupBy("tbl", "model", "subset").agg(F.sum(F.when(F.col("hit"), F.col("n_chars")).when(F.col("hit").isNotNull(), 0)).alias("bad"), chars(F.col("hit").isNotNull()).alias("all"), F.count_if("hit").alias("hits"), F.count("hit").alias("n"))
    values = F.explode(F.array(
        F.struct(F.lit("error").alias("metric"), F.try_divide(100.0 * F.col("bad"), F.col("all")).alias("value")),
        F.struct(F.lit("similarity").alias("metric"), (1 - F.try_divide(F.col("hits"), F.col("n"))).alias("value")),
    )).alias("v")
    return sums.select("tbl", "model", "subset", values).select("tbl", "model", "subset", "v.*")


@query("i13_relative", MEASURED + f" SELECT tbl, subset, metric, round(base, 6) AS base, round(new, 6) AS new, round(gain, 6) AS gain FROM {_relative('gen2', 'new_l').replace('/ o.value', '/ nullif(o.value, 0)')}")
def i13_relative(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(metrics.relative(measured(spark, sf_dir), "gen2", "new_l"))


@query("i14_podium", MEASURED + " SELECT tbl, model, subset, metric, value, CASE WHEN value IS NOT NULL THEN dense_rank() OVER (PARTITION BY tbl, subset, metric, value IS NULL ORDER BY CASE WHEN metric IN ('cer', 'wer', 'error') THEN value ELSE -value END)::INT END AS rank FROM cells")
def i14_podium(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.podium(measured(spark, sf_dir))


@query("i15_fill", MEASURED + " SELECT tbl, model, subset, metric, coalesce(value, CASE WHEN metric IN ('cer', 'wer', 'error') THEN 100.0::DOUBLE ELSE 0.0::DOUBLE END) AS value FROM cells")
def i15_fill(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.fill_unsupported(measured(spark, sf_dir))


@query("i16_table", MEASURED + " SELECT model, max(value) FILTER (WHERE subset = 'de') AS de, max(value) FILTER (WHERE subset = 'en') AS en, max(value) FILTER (WHERE subset = 'es') AS es, max(value) FILTER (WHERE subset = 'fr') AS fr FROM cells WHERE tbl = 'multilingual' AND metric = 'error' GROUP BY model")
def i16_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.table(measured(spark, sf_dir).filter("tbl = 'multilingual' AND metric = 'error'"), "model", "subset", ["de", "en", "es", "fr"])


@query("i17_size_gap", MEASURED + " SELECT tbl, subset, metric, round(max(value) FILTER (WHERE model = 'new_l') - max(value) FILTER (WHERE model = 'new_s'), 6) AS gap FROM cells GROUP BY tbl, subset, metric")
def i17_size_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(metrics.size_gap(measured(spark, sf_dir), "new_s", "new_l"))


@query("i18_volume", "SELECT count(*) AS n, count(DISTINCT lang) AS languages, count(DISTINCT source) AS dialects, round(sum(n_chars) / 54000.0::DOUBLE, 6) AS hours, (sum(n_chars) * 25 // 15)::BIGINT AS tokens FROM documents")
def i18_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return docs.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("lang").alias("languages"), F.countDistinct("source").alias("dialects"), F.round(F.sum("n_chars") / 54000.0, 6).alias("hours"), F.floor(F.sum("n_chars") * 25 / 15).alias("tokens"))


W = " + ".join(f"CASE WHEN u > {p}::DOUBLE THEN 1 ELSE 0 END" for p in err.POISSON_ONE)


@query("i19_bootstrap", SCORED + f", u AS (SELECT system, edits, n_ref, b, {sql_uniform(chr(39) + 'boot' + chr(39), 'utt_id', 'b')} AS u FROM sc, range(1, 21) AS r(b)) SELECT system, b::INT AS replicate, round(sum(({W}) * edits) / sum(({W}) * n_ref)::DOUBLE, 6) AS micro FROM u GROUP BY system, b")
def i19_bootstrap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(err.bootstrap(_scored(spark, sf_dir), "system", "utt_id", 20))


@query("i19_interval", SCORED + f", u AS (SELECT system, edits, n_ref, b, {sql_uniform(chr(39) + 'boot' + chr(39), 'utt_id', 'b')} AS u FROM sc, range(1, 201) AS r(b)), x AS (SELECT system, b, sum(({W}) * edits) / sum(({W}) * n_ref)::DOUBLE AS micro FROM u GROUP BY system, b) SELECT system, round(quantile_cont(micro, 0.025), 6) AS low, round(quantile_cont(micro, 0.975), 6) AS high FROM x GROUP BY system")
def i19_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds that hold 95 % of 200 replicates: a system's replicates are few, whatever the corpus."""
    reps = err.bootstrap(_scored(spark, sf_dir), "system", "utt_id", 200)
    return _r(reps.groupBy("system").agg(F.percentile("micro", F.lit(0.025)).alias("low"), F.percentile("micro", F.lit(0.975)).alias("high")))


@query("i19_sign_test", SCORED + " SELECT a.system AS s1, b.system AS s2, count(*) FILTER (WHERE a.edits < b.edits) AS wins, count(*) FILTER (WHERE a.edits > b.edits) AS losses, round((count(*) FILTER (WHERE a.edits < b.edits) - count(*) FILTER (WHERE a.edits > b.edits)) / sqrt(nullif(count(*) FILTER (WHERE a.edits <> b.edits), 0)::DOUBLE), 6) AS z FROM sc a JOIN sc b ON a.utt_id = b.utt_id AND a.system < b.system GROUP BY 1, 2")
def i19_sign_test(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paired by utterance: how often either system has fewer errors, ties left out, and the normal score of the difference."""
    rows = _scored(spark, sf_dir).groupBy("utt_id").agg(F.array_sort(F.collect_list(F.struct("system", "edits"))).alias("ss"))
    pairs = F.flatten(F.transform("ss", lambda a: F.transform(F.filter(F.col("ss"), lambda b: b["system"] > a["system"]), lambda b: F.struct(a["system"].alias("s1"), b["system"].alias("s2"), (a["edits"] - b["edits"]).alias("d")))))
    by = rows.select(F.explode(pairs).alias("p")).select("p.*").groupBy("s1", "s2").agg(F.count_if(F.col("d") < 0).alias("wins"), F.count_if(F.col("d") > 0).alias("losses"))
    return _r(by.withColumn("z", F.try_divide(F.col("wins") - F.col("losses"), F.sqrt((F.col("wins") + F.col("losses")).cast("double")))))


@query("i2a_units", f"WITH t AS ({HEARD}), l AS (SELECT *, CASE WHEN utt_id % 2 = 0 THEN 'zh' ELSE 'en' END AS tongue FROM t) SELECT utt_id, system, tongue, CASE WHEN tongue = 'zh' THEN {sql_char_edits('ref', 'hyp')} ELSE {sql_word_edits('ref', 'hyp')} END::BIGINT AS edits, CASE WHEN tongue = 'zh' THEN length(ref) ELSE len({sql_words('ref')}) END::BIGINT AS n_ref FROM l")
def i2a_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Characters are the unit of some languages, words of the others."""
    tongue = F.when(F.col("utt_id") % 2 == 0, "zh").otherwise("en")
    return err.scored(heard(spark, sf_dir).withColumn("tongue", tongue), unit_of(F.col("tongue"))).select("utt_id", "system", "tongue", "edits", "n_ref")


@query("consensus_pairs", f"WITH t AS ({HEARD}) SELECT a.utt_id, a.system AS s1, b.system AS s2, {sql_word_edits('a.hyp', 'b.hyp')}::BIGINT AS edits FROM t a JOIN t b ON a.utt_id = b.utt_id AND a.system < b.system")
def consensus_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pairs of an utterance's transcripts by a self-join, as the array form of agreement has them without one."""
    rows = heard(spark, sf_dir)
    a, b = rows.alias("a"), rows.alias("b")
    both = a.join(b, (F.col("a.utt_id") == F.col("b.utt_id")) & (F.col("a.system") < F.col("b.system")))
    return both.select("a.utt_id", F.col("a.system").alias("s1"), F.col("b.system").alias("s2"), word_edits(F.col("a.hyp"), F.col("b.hyp")).cast("long").alias("edits"))


@query("i20_bound", P + " SELECT count(value) AS n, count(*) FILTER (WHERE value < 4) AS n_below, coalesce(bool_and(value < 4), true) AS all_below FROM cells WHERE tbl = 'multilingual' AND model = 'new_s+ro'")
def i20_bound(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.below(published.cells(spark).filter("tbl = 'multilingual' AND model = 'new_s+ro'"), 4.0)


@query("i21_continuation", f"WITH t AS ({HEARD}), c AS (SELECT utt_id, system, array_to_string(({sql_words('ref')})[11:], ' ') AS r, array_to_string(({sql_words('hyp')})[11:], ' ') AS h FROM t) SELECT utt_id, system, {sql_word_edits('r', 'h')}::BIGINT AS edits, len({sql_words('r')})::BIGINT AS n_ref FROM c")
def i21_continuation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of the remainder after ten words of prompt."""
    rest = lambda c: F.array_join(F.slice(words(F.col(c)), F.lit(11), F.greatest(F.size(words(F.col(c))) - 10, F.lit(0))), " ")
    rows = heard(spark, sf_dir).withColumns({"ref": rest("ref"), "hyp": rest("hyp")})
    return err.scored(rows, F.lit("word")).select("utt_id", "system", "edits", "n_ref")


@query("i22_gain_gap", P + f" SELECT metric, round(max(gain) FILTER (WHERE subset = 'hard') - max(gain) FILTER (WHERE subset = 'zh'), 6) AS gap FROM {_relative('new_s', 'new_s+ro')} WHERE tbl = 'public' GROUP BY metric")
def i22_gain_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    gains = metrics.relative(published.cells(spark).filter("tbl = 'public'"), "new_s", "new_s+ro")
    return _r(metrics.gain_gap(gains, "hard", "zh"))


@query("i23_wins", P + f" SELECT metric, count(*) FILTER (WHERE gain > 0) AS wins, count(*) FILTER (WHERE gain = 0) AS ties, count(*) FILTER (WHERE gain < 0) AS losses FROM {_relative('new_s', 'new_l')} WHERE tbl = 'cross_lingual' GROUP BY metric")
def i23_wins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.wins(published.cells(spark).filter("tbl = 'cross_lingual'"), "new_l", "new_s")


@query("i23_gain_histogram", P + f" SELECT count(gain) AS n, count(*) FILTER (WHERE gain > 50) AS over_50, count(*) FILTER (WHERE gain BETWEEN 20 AND 50) AS from_20_to_50, count(*) FILTER (WHERE gain < 20) AS below_20 FROM {_relative('new_l', 'new_l+ro')} WHERE tbl = 'cross_lingual'")
def i23_gain_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.gain_histogram(metrics.relative(published.cells(spark).filter("tbl = 'cross_lingual'"), "new_l", "new_l+ro"))
