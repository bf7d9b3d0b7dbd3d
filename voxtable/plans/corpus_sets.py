"""Queries of mixtures, scales and benchmark sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.functions.binding import let
from voxtable.functions.hashing import sql_draw, sql_uniform
from voxtable.functions.shared import stored
from voxtable.functions.units import sql_words, words
from voxtable.operators import bench_sets, mixture, policy, tokens
from voxtable.plans.corpus import TEXTS, texts
from voxtable.registry import query
from voxtable.sources.tables import load

MIX = "WITH mx AS (SELECT doc_id, lang, source, n_chars / 54000.0::DOUBLE AS hours FROM documents)"


def mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select("doc_id", "lang", "source", (F.col("n_chars") / 54000.0).alias("hours"))


def _r(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


@query("g1_rollup", MIX + " SELECT lang, source, round(sum(hours), 6) AS hours, count(*) AS n, grouping_id(lang, source)::BIGINT AS level_id FROM mx GROUP BY ROLLUP (lang, source)")
def g1_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(mixture.hours(mix(spark, sf_dir), ("lang", "source"), "rollup"))


@query("g1_cube", MIX + " SELECT lang, source, round(sum(hours), 6) AS hours, count(*) AS n, grouping_id(lang, source)::BIGINT AS level_id FROM mx GROUP BY CUBE (lang, source)")
def g1_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(mixture.hours(mix(spark, sf_dir), ("lang", "source"), "cube"))


@query("g2_share", MIX + ", s AS (SELECT lang, sum(hours) AS hours FROM mx WHERE lang <> 'en' GROUP BY lang) SELECT lang, round(hours, 6) AS hours, round(hours / sum(hours) OVER (), 6) AS share FROM s")
def g2_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(mixture.share(mix(spark, sf_dir), "lang", ("en",)))


SCALES = {"small": 0.02, "medium": 0.2, "full": 1.0}
U = sql_uniform("'scale'", "doc_id")


@query("g3_scales", MIX + f" SELECT scale, count(*) AS n, round(sum(hours), 6) AS hours FROM mx, (VALUES ('small', 0.02::DOUBLE), ('medium', 0.2::DOUBLE), ('full', 1.0::DOUBLE)) AS s(scale, frac) WHERE {U} < frac GROUP BY scale")
def g3_scales(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mixture.nested_scales(mix(spark, sf_dir), SCALES, "doc_id")
    return _r(rows.groupBy("scale").agg(F.count(F.lit(1)).alias("n"), F.sum("hours").alias("hours")))


BUDGET = {"de": 2.0, "en": 5.0, "es": 1.0, "fr": 1000.0}


@query(
    "g4_budget",
    MIX
    + f""", o AS (SELECT doc_id, lang, hours, coalesce(sum(hours) OVER (PARTITION BY lang ORDER BY {sql_draw("'budget'", 'doc_id')}, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM mx)
    SELECT doc_id, lang FROM o WHERE before < CASE lang WHEN 'de' THEN 2 WHEN 'en' THEN 5 WHEN 'es' THEN 1 ELSE 1000 END""",
)
def g4_budget(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.to_budget(mix(spark, sf_dir), BUDGET, "lang", "doc_id").select("doc_id", "lang")


@query("g5_rebalance", f"SELECT doc_id, copies FROM (SELECT doc_id, (floor(w) + ({sql_uniform(chr(39) + 'rebalance' + chr(39), 'doc_id')} < w - floor(w))::INT)::INT AS copies FROM (SELECT doc_id, CASE lang WHEN 'en' THEN 0.4::DOUBLE WHEN 'de' THEN 1.5::DOUBLE WHEN 'es' THEN 2.25::DOUBLE ELSE 1.0::DOUBLE END AS w FROM documents)) WHERE copies > 0")
def g5_rebalance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.rebalance(mix(spark, sf_dir), {"en": 0.4, "de": 1.5, "es": 2.25}, "lang", "doc_id").select("doc_id", "copies")


@query("g6_coverage", "SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'es') AS es, count(*) FILTER (WHERE lang = 'fr') AS fr FROM documents GROUP BY source")
def g6_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.coverage(load(spark, sf_dir, "documents"), "source", "lang", ["de", "en", "es", "fr"])


RARE = f"WITH u AS ({TEXTS}), w AS (SELECT utt_id, unnest(list_distinct(list_filter(regexp_split_to_array(trim(text), '\\s+'), lambda x: x <> ''))) AS word FROM u), c AS (SELECT word, count(*) AS df, min(utt_id) AS utt_id FROM w GROUP BY word) SELECT word, df, utt_id FROM c WHERE df <= 2 ORDER BY df, word LIMIT 50"


@query("g7_rare", RARE)
def g7_rare(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.rare_cases(texts(spark, sf_dir), words(F.col("text")), "utt_id", 2, 50)


@query("g11_self_train", f"SELECT word || ' ' || word AS text, 'self' AS part FROM ({RARE})")
def g11_self_train(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.self_train(g7_rare(spark, sf_dir))


@query("g8_models", f"WITH w AS (SELECT DISTINCT lang, unnest({sql_words('text')}) AS word FROM documents), p AS (SELECT lang, 'lm' AS part, word AS x FROM w UNION SELECT lang, 'renderer', unnest(string_split(lower(regexp_replace(word, '[^\\p{{L}}]', '', 'g')), '')) FROM w) SELECT lang AS model, count(*) FILTER (WHERE part = 'lm') AS lm_params, count(*) FILTER (WHERE part = 'renderer' AND x <> '') AS renderer_params FROM p GROUP BY lang")
def g8_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A card for each language's counted models: one count for each word, one for each letter."""
    seen = load(spark, sf_dir, "documents").select("lang", F.explode(F.split("text", r"\s+")).alias("word")).filter("word <> ''").distinct()
    return mixture.model_card(seen, "lang", F.col("word"), F.filter(F.split(F.lower(F.regexp_replace("word", r"[^\p{L}]", "")), ""), lambda c: c != ""))


def letters() -> Column:
    """A text's letters, lower case, as tokens."""
    return F.filter(F.split(F.lower(F.regexp_replace("text", r"[^\p{L}]", "")), ""), lambda c: c != "")


CHARS = r"WITH tx AS (SELECT doc_id, lang, lower(regexp_replace(text, '[^\p{L}]', '', 'g')) AS t FROM documents), ch AS (SELECT doc_id, lang, unnest(range(length(t))) AS pos, unnest(string_split(t, '')) AS c FROM tx WHERE t <> '')"
CCTX = CHARS + ", cx AS (SELECT *, coalesce(lag(c) OVER (PARTITION BY doc_id ORDER BY pos), '^') AS ctx FROM ch)"


def _scaled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Perplexity of every document's letters under pair counts of nested subsets."""
    docs = load(spark, sf_dir, "documents")
    subsets = {scale: mixture.uniform("scale", F.col("doc_id")) < frac for scale, frac in SCALES.items()}
    fracs = F.create_map(*[F.lit(x) for kv in SCALES.items() for x in kv])
    out = policy.nested_perplexity(docs, letters(), subsets, 64)
    return out.select(F.col("subset").alias("scale"), fracs[F.col("subset")].alias("frac"), "n", "perplexity")


def _scaled_sql() -> str:
    one = lambda s, f: f"""SELECT '{s}' AS scale, {f}::DOUBLE AS frac, count(*) AS n, exp(-avg(ln((coalesce(k.n, 0) + 1.0::DOUBLE) / (coalesce(t.n, 0) + 64.0::DOUBLE)))) AS perplexity FROM cx
      LEFT JOIN (SELECT ctx, c, count(*) AS n FROM cx WHERE {U} < {f}::DOUBLE GROUP BY 1, 2) k USING (ctx, c) LEFT JOIN (SELECT ctx, count(*) AS n FROM cx WHERE {U} < {f}::DOUBLE GROUP BY 1) t USING (ctx)"""  # noqa: E731
    return " UNION ALL ".join(one(s, f) for s, f in SCALES.items())


@query("g9_plateau", CCTX + f", sc AS ({_scaled_sql()}) SELECT scale, n, round(perplexity, 4) AS perplexity, round((lag(perplexity) OVER w - perplexity) / lag(perplexity) OVER w, 4) AS gain FROM sc WINDOW w AS (ORDER BY frac)")
def g9_plateau(spark: SparkSession, sf_dir: str) -> DataFrame:
    from voxtable.operators.metrics import scaling_gain

    return _r(scaling_gain(_scaled(spark, sf_dir), "frac", "perplexity").select("scale", "n", "perplexity", "gain"), 4)


@query("g10_lineage", "WITH RECURSIVE s AS (SELECT r_name AS stage, NULL AS after FROM region UNION SELECT n_name, r_name FROM nation JOIN region ON r_regionkey = n_regionkey UNION SELECT n_name || '/' || c_mktsegment, n_name FROM customer JOIN nation ON n_nationkey = c_nationkey UNION SELECT n_name || '/' || c_mktsegment || '/' || o_orderpriority, n_name || '/' || c_mktsegment FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey), w AS (SELECT stage, 0 AS depth, stage AS path FROM s WHERE after IS NULL UNION ALL SELECT s.stage, depth + 1, path || ' > ' || s.stage FROM w JOIN s ON s.after = w.stage) SELECT stage, depth, path FROM w")
def g10_lineage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where orders come from: region, nation, market segment, priority; each step names the one before."""
    region, nation, customer, orders = (load(spark, sf_dir, t) for t in ("region", "nation", "customer", "orders"))
    nations = nation.join(region, nation["n_regionkey"] == region["r_regionkey"], "left").select("n_nationkey", "n_name", "r_name")
    people = customer.join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", F.concat("n_name", F.lit("/"), "c_mktsegment").alias("segment"))
    ordered = orders.join(people, F.col("o_custkey") == F.col("c_custkey")).select("segment", "o_orderpriority").distinct()
    steps = (
        region.select(F.col("r_name").alias("stage"), F.lit(None).cast("string").alias("after"))
        .unionAll(nations.filter("r_name IS NOT NULL").select("n_name", "r_name"))
        .unionAll(people.select("segment", "n_name").distinct())
        .unionAll(ordered.select(F.concat("segment", F.lit("/"), "o_orderpriority"), "segment"))
    )
    return mixture.lineage(stored(steps.distinct()))


@query("g12_holdout", CCTX + ", fit AS (SELECT ctx, c, lang, count(*) AS n FROM cx WHERE lang <> 'es' GROUP BY ALL), pk AS (SELECT ctx, c, sum(n) AS n, max(n) AS hit FROM fit GROUP BY ctx, c), kn AS (SELECT lang, count(*) AS n, count(pk.ctx) AS known FROM cx LEFT JOIN pk USING (ctx, c) WHERE lang = 'es' GROUP BY lang) SELECT lang, n, known, round(known / n::DOUBLE, 6) AS share FROM kn")
def g12_holdout(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Letter pairs of a language that was left out, and how many of them the others have shown."""
    ls = letters()
    pairs = F.explode(let(ls, lambda t: F.zip_with(F.slice(F.concat(F.array(F.lit("^")), t), F.lit(1), F.size(t)), t, lambda a, b: F.struct(a.alias("ctx"), b.alias("c")))))
    counts = load(spark, sf_dir, "documents").select("lang", pairs.alias("p")).groupBy("lang", "p").agg(F.count(F.lit(1)).alias("n"))
    seen, held = mixture.holdout(counts, "lang", ("es",))
    known = seen.select("p").distinct().withColumn("known", F.lit(True))
    held = held.join(known, "p", "left").groupBy("lang").agg(F.sum("n").alias("n"), F.sum(F.when(F.col("known"), F.col("n")).otherwise(0)).alias("known"))
    return _r(held.withColumn("share", F.col("known") / F.col("n")))


@query("g13_tokenizer_hours", "SELECT source AS task, round(sum(n_chars) / 54000000.0::DOUBLE, 6) AS khours, round(sum(n_chars)::DOUBLE / sum(sum(n_chars)) OVER ()::DOUBLE, 6) AS share FROM documents GROUP BY source")
def g13_tokenizer_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Thousands of hours by source, each source being a task; characters are summed, so no order of adding shows."""
    parts = mixture.share(load(spark, sf_dir, "documents"), "source", measure="n_chars")
    return _r(parts.select(F.col("source").alias("task"), (F.col("hours") / (1000.0 * mixture.CHARS_PER_HOUR)).alias("khours"), "share"))


def _strat(table: str, by: str, n: int, key: str, seed: str, where: str = "true") -> str:
    return f"SELECT *, row_number() OVER (PARTITION BY {by} ORDER BY {sql_draw(chr(39) + seed + chr(39), key)}, {key}) AS rank FROM {table} WHERE {where} QUALIFY rank <= {n}"


@query("h1_multilingual", f"SELECT lang, doc_id, rank::INT AS rank FROM ({_strat('documents', 'lang', 500, 'doc_id', 'multi')})")
def h1_multilingual(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bench_sets.stratified(load(spark, sf_dir, "documents"), ("lang",), 500, "doc_id", "multi").select("lang", "doc_id", "rank")


HARD = f"""WITH u AS ({TEXTS}), t AS (SELECT utt_id, lang, list_filter(regexp_split_to_array(trim(lower(text)), '\\s+'), lambda x: x <> '') AS w FROM u), i AS (SELECT utt_id, unnest(list_distinct(w)) AS x FROM t), d AS (SELECT x, count(*) AS df FROM i GROUP BY x),
 ra AS (SELECT utt_id, avg(1.0::DOUBLE / df) AS rarity FROM i JOIN d USING (x) GROUP BY utt_id), sh AS (SELECT utt_id, lang, CASE WHEN len(w) > 1 THEN len(list_filter(range(1, len(w)), lambda k: w[k][1:1] = w[k + 1][1:1])) / (len(w) - 1)::DOUBLE END AS al, CASE WHEN len(w) > 0 THEN 1 - len(list_distinct(w)) / len(w)::DOUBLE END AS rep FROM t),
 hd AS (SELECT lang, utt_id, round(coalesce(rarity, 0) + coalesce(al, 0) + coalesce(rep, 0), 9) AS score FROM sh LEFT JOIN ra USING (utt_id)) SELECT lang, utt_id, round(score, 6) AS score FROM hd QUALIFY row_number() OVER (PARTITION BY lang ORDER BY score DESC, utt_id) <= 20"""


@query("h2_hard", HARD)
def h2_hard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(bench_sets.hard(texts(spark, sf_dir), "utt_id", 20).select("lang", "utt_id", "score"))


@query(
    "h3_cross_lingual",
    f"""WITH p AS ({_strat('documents', 'lang', 50, 'doc_id', 'prompt')}), t AS ({_strat('documents', 'lang', 50, 'doc_id', 'target')})
    SELECT p.lang AS prompt_lang, t.lang AS target_lang, p.rank::INT AS rank, p.doc_id AS prompt_id, t.doc_id AS target_id FROM p JOIN t ON p.rank = t.rank AND p.lang <> t.lang""",
)
def h3_cross_lingual(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang")
    return bench_sets.cross_lingual(docs, docs, ["de", "en", "es", "fr"], 50, "doc_id")


EMO = f"WITH e AS (SELECT l.doc_id, d.lang, CASE WHEN toxic = 1 THEN 'angry' WHEN quality = 1 THEN 'happy' ELSE 'sad' END AS emotion, CASE WHEN {sql_draw(chr(39) + 'related' + chr(39), 'l.doc_id')} % 2 = 0 THEN 'related' ELSE 'unrelated' END AS relation FROM labels l JOIN documents d USING (doc_id))"


def emotions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, lang, emotion, relation: three emotions from the labels; a hashed half of the texts is related to it."""
    rows = load(spark, sf_dir, "labels").join(load(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id")
    emotion = F.when(F.col("toxic") == 1, "angry").when(F.col("quality") == 1, "happy").otherwise("sad")
    return rows.select("doc_id", "lang", emotion.alias("emotion"), F.when(bench_sets.draw("related", F.col("doc_id")) % 2 == 0, "related").otherwise("unrelated").alias("relation"))


@query("h4_emotion", EMO + f" SELECT lang, emotion, relation, doc_id FROM ({_strat('e', 'lang, emotion, relation', 10, 'doc_id', 'emotion')})")
def h4_emotion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bench_sets.stratified(emotions(spark, sf_dir), ("lang", "emotion", "relation"), 10, "doc_id", "emotion").select("lang", "emotion", "relation", "doc_id")


@query("h5_expressive", "SELECT event_id, CASE WHEN value <= lo THEN 'low' ELSE 'high' END AS tail FROM events, (SELECT quantile_cont(value, 0.02) AS lo, quantile_cont(value, 0.98) AS hi FROM events) WHERE value <= lo OR value >= hi")
def h5_expressive(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bench_sets.tails(load(spark, sf_dir, "events").select("event_id", "value"), "value", 0.02, 0.98).select("event_id", "tail")


SEQ = "SELECT user_id, list(least(4, floor(value / 25))::INT ORDER BY event_id) AS s FROM events GROUP BY user_id"


@query("h6_continuation", f"SELECT user_id, list_sum(s[1:75])::BIGINT AS prompt_sum, coalesce(list_sum(s[76:]), 0)::BIGINT AS rest_sum, len(s) - len(s[1:75]) AS rest_len FROM ({SEQ}) ORDER BY {sql_draw(chr(39) + 'cont' + chr(39), 'user_id')}, user_id LIMIT 120")
def h6_continuation(spark: SparkSession, sf_dir: str) -> DataFrame:
    seq = load(spark, sf_dir, "events").select("user_id", F.col("event_id").alias("t"), F.least(F.lit(4), F.floor(F.col("value") / 25)).cast("int").alias("token"))
    packed = tokens.pack(seq, "user_id")
    prompt, rest = bench_sets.continuation(F.col("tokens"))
    total = lambda a: F.aggregate(a, F.lit(0).cast("long"), lambda s, x: s + x)
    chosen = packed.orderBy(bench_sets.draw("cont", F.col("user_id")), "user_id").limit(120)
    return chosen.select("user_id", total(prompt).alias("prompt_sum"), total(rest).alias("rest_sum"), F.size(rest).cast("long").alias("rest_len"))


@query("h7_dialects", f"WITH g AS (SELECT source FROM documents GROUP BY source ORDER BY count(*) DESC, source LIMIT 18) SELECT source, doc_id FROM ({_strat('documents', 'source', 10, 'doc_id', 'dialect')}) WHERE source IN (SELECT source FROM g)")
def h7_dialects(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "source")
    groups = docs.groupBy("source").count().orderBy(F.desc("count"), "source").limit(18).select("source")
    return bench_sets.stratified(docs.join(F.broadcast(groups), "source"), ("source",), 10, "doc_id", "dialect").select("source", "doc_id")


@query("h8_three_way", f"SELECT item_id, CASE {sql_draw(chr(39) + 'split' + chr(39), 'item_id')} % 3 WHEN 0 THEN 'zh' WHEN 1 THEN 'en' ELSE 'hard' END AS subset FROM benchmark")
def h8_three_way(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "benchmark").select("item_id", F.element_at(F.array(F.lit("zh"), F.lit("en"), F.lit("hard")), (bench_sets.draw("split", F.col("item_id")) % 3).cast("int") + 1).alias("subset"))


@query("h9_pair", f"WITH o AS (SELECT doc_id, lang, lead(doc_id) OVER w AS nx, first_value(doc_id) OVER w AS fs FROM documents WINDOW w AS (PARTITION BY lang ORDER BY {sql_draw(chr(39) + 'pair' + chr(39), 'doc_id')}, doc_id)) SELECT doc_id, coalesce(nx, fs) AS partner FROM o WHERE coalesce(nx, fs) <> doc_id")
def h9_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bench_sets.pair(load(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id", "lang").select("doc_id", "partner")


@query("h10_leakage", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def h10_leakage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bench_sets.leakage(load(spark, sf_dir, "documents").select("doc_id", "text"), load(spark, sf_dir, "benchmark"), "doc_id")
