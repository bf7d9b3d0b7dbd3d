"""Findings of the second review: odd values, and given tables in place of made-up ones."""

import os
import shutil
import tempfile
from pathlib import Path

from pyspark.sql import functions as F

from tests.oracle import same
from voxtable import plans, registry

plans.register_all()


def _tables(tmp_path, spark, **frames):
    """A folder of the smallest tables with some of them replaced."""
    for t in os.listdir("/root/testdata/sf0.001"):
        os.symlink(f"/root/testdata/sf0.001/{t}", tmp_path / t) if t.removesuffix(".parquet") not in frames else None
    for t, df in frames.items():
        df.coalesce(1).write.parquet(str(tmp_path / f"{t}-written"))
        shutil.copy(next((tmp_path / f"{t}-written").glob("part-*.parquet")), tmp_path / f"{t}.parquet")
    return str(tmp_path)


def _same(spark, sf_dir, name):
    same(spark, sf_dir, registry.QUERIES[name], registry.ORACLES[name])


def test_math_suite_of_nothing_and_of_less(spark, sf_dir, tmp_path):
    e = spark.read.parquet(f"{sf_dir}/events.parquet").limit(40).withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    odd = e.withColumn("value", F.when(F.col("event_id") % 4 == 0, F.lit(0.0)).when(F.col("event_id") % 4 == 1, -F.col("value")).when(F.col("event_id") % 4 == 2, F.col("value")))
    folder = _tables(tmp_path, spark, events=odd.withColumn("user_id", -F.col("user_id")))
    _same(spark, folder, "math_suite")


def _reads(spark, sf_dir, name, *tables):
    """The query's rows are SQL's, and they change with the table: without its rows nothing is left."""
    same(spark, sf_dir, registry.QUERIES[name], registry.ORACLES[name])
    assert registry.QUERIES[name](spark, sf_dir).count() > 0
    with tempfile.TemporaryDirectory() as folder:
        empty = _tables(Path(folder), spark, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet").limit(0) for t in tables})
        assert registry.QUERIES[name](spark, empty).count() == 0


def test_cte_recursive_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "cte_recursive", "lineitem")


def test_g10_lineage_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "g10_lineage", "region", "nation", "customer", "orders")


def test_g13_tokenizer_hours_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "g13_tokenizer_hours", "documents")


def test_g8_models_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "g8_models", "documents")


def test_i12_correction_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "i12_correction", "documents")


def test_i13_relative_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "i13_relative", "documents")


def test_i14_podium_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "i14_podium", "documents")


def test_i15_fill_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "i15_fill", "documents")


def test_i16_table_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "i16_table", "documents")


def test_i17_size_gap_reads_a_table(spark, sf_dir):
    _reads(spark, sf_dir, "i17_size_gap", "documents")


def test_scored_words_are_the_transcripts_errors(spark, sf_dir):
    """Against every transcript and the engine's distance, longer texts, blanks, odd languages and keys too; no system's transcripts are made twice."""
    from voxtable.operators import err, surrogate
    from voxtable.plans import experiments
    from voxtable.plans.corpus import utterances

    odd = spark.createDataFrame([(None, "a b c", "en"), (7, None, "en"), (8, "", "fr"), (9, "x\u00a0y \t z " * 90, None), (10, "aba ab", "xx")], "utt_id bigint, text string, lang string")
    rows = odd.unionAll(utterances(spark, sf_dir).select("utt_id", "text", "lang").limit(300))
    said = err.scored(surrogate.transcripts(rows, experiments.MULTI, "lang").filter("hyp IS NOT NULL"), F.lit("word"))
    by = lambda df: {(r["system"], r["lang"]): (r["e"], r["n"]) for r in df.filter("edits IS NOT NULL").groupBy("system", "lang").agg(F.sum("edits").alias("e"), F.sum("n_ref").alias("n")).collect()}
    assert by(surrogate.scored_words(rows, experiments.MULTI, "lang", experiments.LANGS)) == by(said.filter(F.col("lang").isin(*experiments.LANGS)))
    plan = experiments.w1_overview(spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "md5" not in plan and plan.count("ArrowEvalPython") == 1


def test_switches_hear_the_texts_once(spark, sf_dir, monkeypatch):
    from voxtable.plans import corpus

    made = []
    real = corpus.stored
    monkeypatch.setattr(corpus, "stored", lambda df: made.append(1) or real(df))
    corpus.a8_switches(spark, sf_dir)
    assert len(made) == 1


def test_long_credentials_are_found_whole():
    import hashlib

    from voxtable.llm import secret_grammar

    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    body = "".join(letters[b % 62] for k in range(24) for b in hashlib.sha256(b"%d" % k).digest())
    token = f"eyJ{body[:30]}.eyJ{body[30:630]}.{body[630:673]}"
    found = secret_grammar.scan_batch(secret_grammar.Grammar(), [f"see {token} end"])
    assert found["spans"][0] == f"learned:4:{4 + len(token)}"


def test_steps_over_arrays_equal_the_engines(spark, sf_dir):
    """Transcripts and pauses drawn over arrays, odd texts and keys too; the corpus steps draw no md5 in the engine."""
    from voxtable.operators import consensus, punct
    from voxtable.plans import corpus

    odd = [(None, "a b, c"), (7, None), (8, ""), (9, "x y, \t z! " * 90), (10, " ab,\u0085 c  d.  ,, e "), (11, "été \U0001f600, " * 30), (12, "\n")]
    rows = spark.createDataFrame([(k, t, "en") for k, t in odd], "utt_id bigint, text string, lang string")
    rows = rows.unionAll(corpus.utterances(spark, sf_dir).select("utt_id", "text", "lang").limit(300))
    as_sql = consensus.transcribe(rows).groupBy("utt_id").agg(F.array_sort(F.collect_list(F.struct("system", "hyp"))).alias("ts"))
    by = lambda df, col: {r["utt_id"]: r[col] for r in df.collect()}
    assert by(consensus.transcribe_together(rows), "ts") == by(as_sql, "ts")
    assert by(punct.adjust_together(rows), "text") == by(punct.adjust(rows), "text")
    assert by(consensus.select(consensus.transcribe_together(rows), pick="medoid", keep=("lang",)).filter("error IS NOT NULL"), "hyp") == by(consensus.select(consensus.transcribe(rows), pick="medoid"), "hyp")
    steps = corpus.run(rows)
    assert not any("md5" in steps[s]._jdf.queryExecution().executedPlan().toString() for s in steps)
    twice = corpus.run(rows.limit(50).unionAll(rows.limit(50)), ("asr",))["asr"]
    assert twice.groupBy("utt_id").count().filter("count <> 2").isEmpty()
