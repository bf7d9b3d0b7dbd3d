"""The experiments' workloads on the given tables: systems are stand-ins, every computation is real."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from voxtable.functions.hashing import draw, sql_draw
from voxtable.functions.units import sql_word_edits, sql_words
from voxtable.functions.vectors import cosine
from voxtable.operators import bench_sets, err, fsq, judged, lexicon, mixture, policy, reward, signal, surrogate, tokens, vq
from voxtable.plans import corpus, corpus_sets, measures, published, rewards, speech_tokens, text_side
from voxtable.plans.corpus import UTT, sql_corrupt, utterances
from voxtable import registry
from voxtable.registry import query
from voxtable.sources.tables import load

P = measures.P


def _r(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _supported_sql() -> str:
    cases = " ".join(f"WHEN '{s}' THEN lang IN ({', '.join(repr(x) for x in langs)})" for s, langs in surrogate.SUPPORTED.items())
    return f"CASE system {cases} ELSE true END"


def _error_table(rows: str, systems: list[str], cols: list[str], col: str = "lang", support: bool = True) -> str:
    heard = sql_corrupt({s: surrogate.SYSTEMS[s] for s in systems}, rows)
    ok = _supported_sql() if support else "true"
    cell = lambda c: f"round(100 * sum(edits) FILTER (WHERE {col} = '{c}') / nullif(sum(n_ref) FILTER (WHERE {col} = '{c}'), 0)::DOUBLE, 4) AS {c}"
    return f"WITH t AS ({heard}), h AS (SELECT *, {ok} AS ok FROM t), s AS (SELECT system, {col}, {sql_word_edits('ref', 'hyp')} AS edits, len({sql_words('ref')}) AS n_ref FROM h WHERE ok) SELECT y.system, {', '.join(cols)} FROM (SELECT DISTINCT system FROM t) y LEFT JOIN (SELECT system, {', '.join(map(cell, cols))} FROM s GROUP BY system) z USING (system)"


def _error_pivot(rows: DataFrame, systems: list[str], cols: list[str], col: str = "lang") -> DataFrame:
    """system x column matrix of micro word error in percent; null where nothing is supported."""
    scored = surrogate.scored_words(rows, systems, col, cols)
    rates = scored.groupBy("system", col).agg((100.0 * F.try_divide(F.sum("edits"), F.sum("n_ref"))).alias("rate"))
    return _r(rates.groupBy("system").pivot(col, cols).agg(F.first("rate")), 4)


T4 = [s for s in surrogate.SYSTEMS if s not in ("gen2+ro",)]


@query("w2_public", _error_table("SELECT item_id AS utt_id, text, 'en' AS lang FROM benchmark", T4, ["en"], support=False))
def w2_public(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("utt_id"), "text", F.lit("en").alias("lang"))
    return _error_pivot(items, T4, ["en"])


LANGS = ["de", "en", "es", "fr"]
MULTI = ["nar_3", "ar_4", "gen2", "gen2+ro", "new_s", "new_s+ro", "new_l", "new_l+ro"]


@query("w3_multilingual", _error_table(UTT, MULTI, LANGS))
def w3_multilingual(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _error_pivot(utterances(spark, sf_dir), MULTI, LANGS)


HARD = ["gen2", "gen2+ro", "new_s", "new_s+ro", "new_l", "new_l+ro"]


@query("w4_hard", _error_table(f"SELECT u.utt_id, u.text, u.lang FROM ({UTT}) u JOIN ({corpus_sets.HARD}) h ON h.utt_id = u.doc_id", HARD, LANGS))
def w4_hard(spark: SparkSession, sf_dir: str) -> DataFrame:
    chosen = bench_sets.hard(corpus.texts(spark, sf_dir), "utt_id", 20).select(F.col("utt_id").alias("doc_id"))
    return _error_pivot(utterances(spark, sf_dir).join(chosen, "doc_id"), HARD, LANGS)


CROSS = ["gen2", "new_s", "new_s+ro", "new_l", "new_l+ro"]
DIRECTIONS = [f"{a}_{b}" for a in LANGS for b in LANGS if a != b]
CROSS_SQL = f"""SELECT u.utt_id * 4 + CASE prompt_lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END AS utt_id, u.text, target_lang AS lang, prompt_lang || '_' || target_lang AS direction FROM (
  WITH p AS ({corpus_sets._strat('documents', 'lang', 50, 'doc_id', 'prompt')}), t AS ({corpus_sets._strat('documents', 'lang', 50, 'doc_id', 'target')})
  SELECT p.lang AS prompt_lang, t.lang AS target_lang, t.doc_id AS target_id FROM p JOIN t ON p.rank = t.rank AND p.lang <> t.lang) c JOIN ({UTT}) u ON u.doc_id = c.target_id"""


def cross(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Target texts of prompt-target pairs, each with its direction; one text under another prompt language is another utterance."""
    pairs = corpus_sets.h3_cross_lingual(spark, sf_dir)
    code = F.array_position(F.array(*map(F.lit, LANGS)), F.col("prompt_lang")) - 1
    texts = utterances(spark, sf_dir).select(F.col("doc_id").alias("target_id"), "utt_id", "text")
    return pairs.join(texts, "target_id").select((F.col("utt_id") * 4 + code).alias("utt_id"), "text", F.col("target_lang").alias("lang"), F.concat_ws("_", "prompt_lang", "target_lang").alias("direction"))


def _directed(systems: list[str], cols: list[str]) -> str:
    return _error_table(CROSS_SQL, systems, cols, "direction").replace("SELECT utt_id, lang, system, text AS ref", "SELECT utt_id, lang, direction, system, text AS ref", 1)


@query("w5_cross_lingual", _directed(CROSS, DIRECTIONS))
def w5_cross_lingual(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _error_pivot(cross(spark, sf_dir), CROSS, DIRECTIONS, "direction")


PAIR = ["nar_3", "ar_4", "gen2", "new_s", "new_l"]


@query("w6_two_directions", _directed(PAIR, ["en_fr", "fr_en"]))
def w6_two_directions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _error_pivot(cross(spark, sf_dir).filter("direction IN ('en_fr', 'fr_en')"), PAIR, ["en_fr", "fr_en"], "direction")


@query("w1_overview", f"SELECT system, 'de' AS subset, coalesce(de, 100.0::DOUBLE) AS error FROM ({_error_table(UTT, MULTI, LANGS)}) UNION ALL SELECT system, 'en', coalesce(en, 100.0::DOUBLE) FROM ({_error_table(UTT, MULTI, LANGS)})")
def w1_overview(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As plotted: unsupported languages count as an error of 100."""
    wide = _error_pivot(utterances(spark, sf_dir), MULTI, ["de", "en"])  # no other language's errors are shown
    return wide.select("system", F.expr("stack(2, 'de', de, 'en', en) AS (subset, error)")).withColumn("error", F.coalesce("error", F.lit(100.0)))


@query("w7_emotion", measures.GUESSED + " SELECT relation, round(avg((pred = emotion)::INT) FILTER (WHERE emotion = 'angry'), 6) AS angry, round(avg((pred = emotion)::INT) FILTER (WHERE emotion = 'happy'), 6) AS happy, round(avg((pred = emotion)::INT) FILTER (WHERE emotion = 'sad'), 6) AS sad FROM gs GROUP BY relation")
def w7_emotion(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = judged.accuracy(measures.guessed(spark, sf_dir), "relation", "emotion")
    return _r(by.groupBy("relation").pivot("emotion", ["angry", "happy", "sad"]).agg(F.first("accuracy")))


@query("w8_opinion", measures.RATED + " SELECT system, round(avg(score) FILTER (WHERE lang = 'zh'), 6) AS zh, round(avg(score) FILTER (WHERE lang = 'en'), 6) AS en, round(avg(score), 6) AS pooled FROM rt GROUP BY system")
def w8_opinion(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = judged.opinion(judged.ratings(load(spark, sf_dir, "events")))
    pick = lambda v, n: F.max(F.when(F.col("lang").eqNullSafe(v), F.col("mos"))).alias(n)
    return _r(o.groupBy("system").agg(pick("zh", "zh"), pick("en", "en"), pick(None, "pooled")))


VIEW_B = fsq.FsqSpec(width=32, first=32)
VIEW_A = fsq.FsqSpec(width=32)
PROBE = "SELECT '{name}' AS tokenizer, round(1 - sum(hit) / sum(n)::DOUBLE, 6) AS error FROM (SELECT token, max(n) AS hit, sum(n) AS n FROM (SELECT token, label, count(*) AS n FROM ({tok}) GROUP BY token, label) GROUP BY token)"
VQ_SQL = f"SELECT label, {speech_tokens._nearest('embedding', speech_tokens.BOOK)} AS token FROM embeddings"


@query("w9_quantisers", PROBE.format(name="scalar_a", tok=speech_tokens.tok_sql(VIEW_A)) + " UNION ALL " + PROBE.format(name="scalar_b", tok=speech_tokens.tok_sql(VIEW_B)) + " UNION ALL " + PROBE.format(name="vector", tok=VQ_SQL) + f" UNION ALL SELECT 'continuous', round(1 - accuracy, 6) FROM ({registry.ORACLES['b16_probe_centroid']})")
def w9_quantisers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of the label read off the token: scalar quantiser on two views, vector quantiser; and off the vector itself, the upper bound."""
    rows = load(spark, sf_dir, "embeddings")
    out = tokens.centroid_probe(rows, "label", "embedding").select(F.lit("continuous").alias("tokenizer"), F.round(1 - F.round("accuracy", 6), 6).alias("error"))
    for name, tok in (("scalar_a", fsq.tokenize(rows, VIEW_A)), ("scalar_b", fsq.tokenize(rows, VIEW_B)), ("vector", vq.assign(rows, speech_tokens.BOOK).withColumnRenamed("code", "token"))):
        one = tokens.majority_probe(tok, "token", "label").select(F.lit(name).alias("tokenizer"), F.round(1 - F.col("accuracy"), 6).alias("error"))
        out = out.unionAll(one)
    return out


UNDERSTANDING = {"label": "label", "parity": "label % 2", "tercile": "label div 4", "sign_0": "int(embedding[0] > 0)", "sign_1": "int(embedding[1] > 0)", "sign_2": "int(embedding[2] > 0)"}
UNDERSTANDING_SQL = {**UNDERSTANDING, "tercile": "label // 4", "sign_0": "(embedding[1] > 0)::INT", "sign_1": "(embedding[2] > 0)::INT", "sign_2": "(embedding[3] > 0)::INT"}


@query("w10_understanding", " UNION ALL ".join(f"SELECT '{t}' AS task, round(sum(hit) / sum(n)::DOUBLE, 6) AS accuracy FROM (SELECT token, max(n) AS hit, sum(n) AS n FROM (SELECT token, {e} AS truth, count(*) AS n FROM ({speech_tokens.tok_sql(speech_tokens.SPEC)}) GROUP BY 1, 2) GROUP BY token)" for t, e in UNDERSTANDING_SQL.items()))
def w10_understanding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six tasks read off the token: one scan, one shuffle by (task, token)."""
    tok = fsq.tokenize(load(spark, sf_dir, "embeddings"), speech_tokens.SPEC)
    each = F.array(*[F.struct(F.lit(t).alias("task"), F.expr(e).alias("truth")) for t, e in UNDERSTANDING.items()])
    long = tok.select("token", F.explode(each).alias("x")).select("token", "x.*")
    by = long.groupBy("task", "token", "truth").agg(F.count(F.lit(1)).alias("n")).groupBy("task", "token").agg(F.max("n").alias("hit"), F.sum("n").alias("n"))
    return by.groupBy("task").agg(F.round(F.sum("hit") / F.sum("n"), 6).alias("accuracy"))


@query("w11_tokenizers")
def w11_tokenizers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five tokenizers at two nested data scales: label error read off the token."""
    rows = load(spark, sf_dir, "embeddings").persist()
    out = None
    for scale, frac in (("small", 0.2), ("full", 1.0)):
        part = rows.filter(mixture.uniform("scale", F.col("vec_id")) < frac)
        views = {
            "acoustic": vq.residual(part, [speech_tokens.BOOK, speech_tokens.BOOK2]).withColumn("token", F.col("codes")[0]),
            "ssl_a": vq.assign(part, vq.fit(part, 8, iters=2)).withColumnRenamed("code", "token"),
            "ssl_b": vq.assign(part.withColumn("embedding", F.slice("embedding", 33, 32)), speech_tokens.literal_book(8, 32)).withColumnRenamed("code", "token"),
            "sup_old": vq.assign(part, speech_tokens.BOOK).withColumnRenamed("code", "token"),
            "sup_new": fsq.tokenize(part, speech_tokens.SPEC),
        }
        for name, tok in views.items():
            one = tokens.majority_probe(tok, "token", "label").select(F.lit(scale).alias("scale"), F.lit(name).alias("tokenizer"), F.round(1 - F.col("accuracy"), 6).alias("error"), "n")
            out = one if out is None else out.unionAll(one)
    return out


@query("w12_data_scaling", corpus_sets.CCTX + f" SELECT scale, n, round(perplexity, 4) AS perplexity FROM ({corpus_sets._scaled_sql()})")
def w12_data_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _r(corpus_sets._scaled(spark, sf_dir).select("scale", "n", "perplexity"), 4)


@query("w13_reward_ablation")
def w13_reward_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Objective, reward and divergence at the start and end of the optimisation, with and without the divergence term."""
    rows = []
    for beta in (0.0, 0.1):
        _, trace = reward.optimize(rewards.start(spark, sf_dir), reward.Settings(iters=8, beta=beta))
        rows += [{"beta": beta, "when": w, **t} for w, t in (("start", trace[0]), ("end", trace[-1]))]
    return reward.trace_frame(spark, rows)


VARIANTS = [("all_phones", "all", "phones"), ("mono_phones", "mono", "phones"), ("mono_both", "mono", "both"), ("all_both", "all", "both")]
POLY = text_side.LEX + ", it AS (SELECT lang, unnest(" + text_side.SYM + ") AS symbol FROM u), e AS (SELECT it.lang, it.symbol, r.phones AS said, nr.pick, nr.n_readings FROM it JOIN rd r ON r.symbol = it.symbol AND r.lang = it.lang JOIN nr ON nr.symbol = it.symbol WHERE nr.pick <> r.phones)"


@query("w14_correction", POLY + f""", v AS (SELECT e.*, variant, CASE WHEN which = 'all' OR n_readings = 1 THEN CASE render WHEN 'both' THEN symbol ELSE '' END || '/' || pick || '/' ELSE symbol END AS shown FROM e, (VALUES {', '.join(map(str, VARIANTS))}) AS x(variant, which, render)),
  h AS (SELECT *, CASE WHEN contains(shown, '/') THEN shown ELSE '/' || said || '/' END AS hinted FROM v)
  SELECT variant, lang, count(*) AS errors, count(*) FILTER (WHERE regexp_extract(hinted, '/(.*)/', 1) = said) AS corrected, round(100.0::DOUBLE * count(*) FILTER (WHERE regexp_extract(hinted, '/(.*)/', 1) = said) / count(*), 6) AS rate FROM h GROUP BY variant, lang""")
def w14_correction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Symbols whose predicted reading is not their language's are errors. Each variant renders them; a user's hint takes the place of a symbol that was left bare;
    what the rendered phones say is then compared with the true reading."""
    rows = corpus.texts(spark, sf_dir)
    lex = lexicon.build(rows)
    wrong = lexicon.placed(rows, lex, "lang").join(lex.select("symbol", "lang", F.col("phones").alias("said")), ["symbol", "lang"]).filter("pick <> said")
    variants = F.explode(F.array(*[F.struct(F.lit(v).alias("variant"), F.lit(w).alias("which"), F.lit(r).alias("render")) for v, w, r in VARIANTS])).alias("x")
    each = wrong.select("lang", "symbol", "said", "pick", "n_readings", variants).select("*", "x.*")
    shown = F.when(lexicon.replaced(F.col("which")), lexicon.piece(F.col("symbol"), F.col("render"))).otherwise(F.col("symbol"))
    hinted = F.when(F.contains("shown", F.lit("/")), F.col("shown")).otherwise(F.concat(F.lit("/"), "said", F.lit("/")))
    heard = F.regexp_extract("hinted", "/(.*)/", 1)
    each = each.withColumn("shown", shown).withColumn("hinted", hinted).select("variant", "lang", F.lit(1).cast("long").alias("errors"), (heard == F.col("said")).cast("long").alias("corrected"))
    return _r(judged.correction_rate(each, "variant", "lang"))


@query("w15_instructed", "WITH c AS (SELECT conv_id, turn, role, (conv_id * 10 + turn) % (SELECT count(*) FROM embeddings) AS vec_id FROM conversations), e AS (SELECT vec_id, label, embedding FROM embeddings), k AS (SELECT label, pos, avg(x) AS m FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings) GROUP BY 1, 2), s AS (SELECT c.role, c.conv_id, c.turn, sum(x * m) / (sqrt(sum(x * x)) * sqrt(sum(m * m))) AS cs FROM c JOIN (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM e) v USING (vec_id) JOIN k ON k.label = v.label AND k.pos = v.pos GROUP BY 1, 2, 3) SELECT role, count(*) AS n, round(100 * avg(cs), 4) AS similarity FROM s GROUP BY role")
def w15_instructed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Style similarity by prompt role, truth being 100."""
    emb = load(spark, sf_dir, "embeddings")
    styled = emb.join(tokens.centroids(emb, "label", "embedding"), "label").select("vec_id", cosine(F.col("embedding"), F.col("centre")).alias("cs"))
    many = emb.agg(F.count(F.lit(1)).alias("many"))  # one row
    rows = load(spark, sf_dir, "conversations").join(F.broadcast(many)).select("role", ((F.col("conv_id") * 10 + F.col("turn")) % F.col("many")).alias("vec_id"))
    return _r(rows.join(styled, "vec_id").groupBy("role").agg(F.count(F.lit(1)).alias("n"), (100 * F.avg("cs")).alias("similarity")), 4)


FINE = ["gen2", "new_s", "new_l"]


SPEAKERS = 10  # target speakers: the labels of the embeddings
SPOKEN_ITEMS = f"SELECT item_id AS utt_id, text, (item_id % {SPEAKERS})::INT AS lang FROM benchmark"


@query("w16_fine_tuned", f"""WITH t AS ({sql_corrupt({s: surrogate.SYSTEMS[s] for s in FINE}, SPOKEN_ITEMS)}), s AS (SELECT system, lang AS speaker, count(*) AS n, round(100 * sum({sql_word_edits('ref', 'hyp')}) / sum(len({sql_words('ref')}))::DOUBLE, 4) AS error FROM t GROUP BY 1, 2),
  e AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings), m AS (SELECT label, pos, avg(x) AS m FROM e GROUP BY 1, 2),
  c AS (SELECT label, vec_id, sum(x * m) / (sqrt(sum(x * x)) * sqrt(sum(m * m))) AS cs FROM e JOIN m USING (label, pos) GROUP BY 1, 2), k AS (SELECT label, round(avg(cs), 4) AS consistency FROM c GROUP BY 1)
  SELECT system, speaker, n, error, consistency FROM s LEFT JOIN k ON k.label = s.speaker""")
def w16_fine_tuned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Error of each base model speaking as each target speaker, and how near the speaker's recordings lie to the centre that stands for them."""
    speaker = (F.col("item_id") % SPEAKERS).cast("int").alias("speaker")
    items = load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("utt_id"), "text", speaker)
    heard = err.scored(surrogate.transcripts(items, FINE, "speaker"), F.lit("word"))
    by = heard.groupBy("system", "speaker").agg(F.count(F.lit(1)).alias("n"), (100.0 * F.try_divide(F.sum("edits"), F.sum("n_ref"))).alias("error"))
    emb = load(spark, sf_dir, "embeddings")
    near = emb.join(tokens.centroids(emb, "label", "embedding"), "label").groupBy(F.col("label").alias("speaker")).agg(F.avg(cosine(F.col("embedding"), F.col("centre"))).alias("consistency"))
    return _r(by.join(near, "speaker", "left").select("system", "speaker", "n", "error", "consistency"), 4)


POLYGLOTS = ["new_s", "new_l+ro"]
VOICED = f"""SELECT u.utt_id, u.text, u.lang, v.speaker FROM (SELECT *, {sql_draw(chr(39) + 'voice' + chr(39), 'utt_id')} AS d FROM ({UTT})) u
  JOIN (SELECT lang, speaker, row_number() OVER (PARTITION BY lang ORDER BY speaker) - 1 AS place, count(*) OVER (PARTITION BY lang) AS many FROM ({text_side.PROMPTS} {text_side.MONO})) v
  ON v.lang = (CASE u.lang WHEN 'de' THEN ['en', 'es', 'fr'] WHEN 'en' THEN ['de', 'es', 'fr'] WHEN 'es' THEN ['de', 'en', 'fr'] ELSE ['de', 'en', 'es'] END)[u.d % 3 + 1] AND v.place = (u.d // 3) % v.many"""


@query("w17_polyglot", f"""WITH vo AS ({VOICED}), t AS ({sql_corrupt({s: surrogate.SYSTEMS[s] for s in POLYGLOTS}, 'SELECT utt_id, text, lang FROM vo')}), s AS (SELECT system, lang, 100 * sum({sql_word_edits('ref', 'hyp')}) / sum(len({sql_words('ref')}))::DOUBLE AS error FROM t GROUP BY 1, 2),
  n AS (SELECT lang, count(DISTINCT speaker) AS speakers, count(*) AS n FROM vo GROUP BY lang) SELECT system, lang, speakers, n, round(error, 4) AS error, error < 4 AS below_bound FROM s JOIN n USING (lang)""")
def w17_polyglot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Monolingual speakers in languages that are not theirs: error by language, and whether it is below the bound of 4."""
    chosen = text_side.f10_select(spark, sf_dir)
    by = Window.partitionBy("lang")
    voices = chosen.select(F.col("lang").alias("home"), "speaker", (F.row_number().over(by.orderBy("speaker")) - 1).alias("place"), F.count(F.lit(1)).over(by).alias("many"))
    d = draw("voice", F.col("utt_id"))
    others = F.create_map(*[x for lang in LANGS for x in (F.lit(lang), F.array(*[F.lit(o) for o in LANGS if o != lang]))])
    rows = utterances(spark, sf_dir).withColumn("d", d).withColumn("home", F.get(F.try_element_at(others, F.col("lang")), (F.col("d") % 3).cast("int")))
    # four languages, five speakers each at most
    voiced = rows.join(F.broadcast(voices), "home").filter(F.col("place") == F.expr("(d div 3) % many")).select("utt_id", "text", "lang", "speaker")
    heard = err.scored(surrogate.transcripts(voiced, POLYGLOTS, "lang", "speaker"), F.lit("word"))
    return _r(
        heard.groupBy("system", "lang").agg(F.countDistinct("speaker").alias("speakers"), F.count(F.lit(1)).alias("n"), (100.0 * F.try_divide(F.sum("edits"), F.sum("n_ref"))).alias("error")).withColumn("below_bound", F.col("error") < 4), 4
    )


@query("w18_pipeline_yield", corpus.YIELD)
def w18_pipeline_yield(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All six steps: segments of the recordings, those not truncated, those whose volume can be set; utterances with an agreed transcript, repunctuated, within the tails."""
    return corpus.all_steps(spark, sf_dir)


@query("w19_tokenizer_hours", corpus.SEG + f", d AS (SELECT rec_id, seg_id, arg_min(kind, (us, frame)) AS task, (max(us) - min(us)) / {corpus.segment.SECOND * 3600}.0::DOUBLE AS hours, CASE WHEN rec_id % 2 = 0 THEN 'zh' ELSE 'en' END AS lang FROM sg GROUP BY rec_id, seg_id) SELECT task, lang, round(sum(hours), 6) AS hours, count(*) AS n, grouping_id(task, lang)::BIGINT AS level_id FROM d GROUP BY ROLLUP (task, lang)")
def w19_tokenizer_hours(spark: SparkSession, sf_dir: str) -> DataFrame:
    seg = corpus._segmented(spark, sf_dir).groupBy("rec_id", "seg_id").agg(F.min_by("kind", F.struct("us", "frame")).alias("task"), ((F.max("us") - F.min("us")) / F.lit(corpus.segment.SECOND * 3600.0)).alias("hours"))
    return _r(mixture.hours(seg.withColumn("lang", F.when(F.col("rec_id") % 2 == 0, "zh").otherwise("en")), ("task", "lang"), "rollup"))


@query("w20_mixture", corpus_sets.MIX + ", l AS (SELECT lang AS part, sum(hours) AS hours FROM mx WHERE lang <> 'en' GROUP BY lang), s AS (SELECT source AS part, sum(hours) AS hours FROM mx GROUP BY source) SELECT 'language' AS dim, part, round(hours / sum(hours) OVER (), 6) AS share FROM l UNION ALL SELECT 'dialect', part, round(hours / sum(hours) OVER (), 6) FROM s")
def w20_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = corpus_sets.mix(spark, sf_dir)
    one = lambda dim, name, out: mixture.share(rows, dim, out).select(F.lit(name).alias("dim"), F.col(dim).alias("part"), F.round("share", 6).alias("share"))
    return one("lang", "language", ("en",)).unionAll(one("source", "dialect", ()))


query("w21_styles", text_side.STYLES)(text_side.f5_styles)


ROUTES = f"""WITH r AS ({text_side.RAW}), n AS (SELECT lang, text, {text_side._norm_sql('text')} AS s, {text_side._norm_sql('text', True)} AS v FROM r), i AS (SELECT *, {text_side._inverse_sql('s')} AS back, {text_side._inverse_sql('v')} AS back_v FROM n)"""


@query("w22_routes", ROUTES + f""", w AS (SELECT 1 AS route, lang, s <> text AS changed, replace(back, ' ', '') = replace(text, ' ', '') AS restored FROM i UNION ALL SELECT 2, lang, v <> text, replace(back_v, ' ', '') = replace(text, ' ', '') FROM i
  UNION ALL SELECT 3, lang, back <> text, {text_side._norm_sql('back')} = s FROM i) SELECT route, lang, count(*) AS n, count(*) FILTER (WHERE changed) AS changed, count(*) FILTER (WHERE restored) AS restored FROM w GROUP BY route, lang""")
def w22_routes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By rules, by the prompted model, by the inverse: rows, rows that change, rows from which the way back leads to the start."""
    norm, back = text_side.textnorm.normalize, text_side.textnorm.denormalize
    lang = F.col("lang")
    rows = text_side.raw_text(spark, sf_dir).select("lang", "text", norm(F.col("text"), lang).alias("s"), norm(F.col("text"), lang, True).alias("v"))
    rows = rows.withColumns({"back": back(F.col("s"), lang), "back_v": back(F.col("v"), lang)})
    bare = lambda c: F.replace(F.col(c), F.lit(" "), F.lit(""))
    way = lambda route, changed, restored: F.struct(F.lit(route).alias("route"), changed.alias("changed"), restored.alias("restored"))
    ways = [way(1, F.col("s") != F.col("text"), bare("back") == bare("text")), way(2, F.col("v") != F.col("text"), bare("back_v") == bare("text")), way(3, F.col("back") != F.col("text"), norm(F.col("back"), lang) == F.col("s"))]
    each = rows.select("lang", F.explode(F.array(*ways)).alias("w")).select("lang", "w.*")
    return each.groupBy("route", "lang").agg(F.count(F.lit(1)).alias("n"), F.count_if("changed").alias("changed"), F.count_if("restored").alias("restored"))


SUBSETS = {"multilingual": "h1_multilingual", "hard": "h2_hard", "cross_lingual": "h3_cross_lingual", "emotion": "h4_emotion", "expressive": "h5_expressive", "continuation": "h6_continuation", "dialects": "h7_dialects", "three_way": "h8_three_way"}


@query("w23_benchmark", " UNION ALL ".join(f"SELECT '{name}' AS subset, count(*) AS n FROM ({registry.ORACLES[q]})" for name, q in SUBSETS.items()))
def w23_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The seven subsets and the public test's split."""
    out = None
    for name, q in SUBSETS.items():
        one = registry.QUERIES[q](spark, sf_dir).agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("subset"), "n")
        out = one if out is None else out.unionAll(one)
    return out


@query("w24_prompts", text_side.PROMPTS + " SELECT (style IS NULL) AS blank_style, count(*) AS n, sum(length(trim(coalesce('Speaker ' || speaker || '.', '') || ' ' || coalesce('Style: ' || style || '.', ''))))::BIGINT AS chars FROM pr GROUP BY 1")
def w24_prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = text_side.prompts(spark, sf_dir)
    shown = text_side.instruct.speaker_style_prompt(F.col("speaker"), F.col("style"))
    return rows.groupBy(F.col("style").isNull().alias("blank_style")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.char_length(shown)).alias("chars"))


CLAIMS = [("public", "gen2", "new_l+ro"), ("public", "new_s", "new_s+ro"), ("public", "new_l", "new_l+ro"), ("multilingual", "gen2", "gen2+ro"), ("multilingual", "new_s", "new_s+ro"), ("multilingual", "new_l", "new_l+ro"), ("cross_lingual", "new_s", "new_s+ro"), ("cross_lingual", "new_l", "new_l+ro"), ("tokenizers", "tok_sup_new_3k", "tok_sup_new_170k"), ("instructed", "gen2", "new_l")]


@query("w26_claims", P + " SELECT * FROM (" + " UNION ALL ".join(f"SELECT tbl, '{a}' AS base_model, '{b}' AS new_model, subset, metric, round(gain, 1) AS gain FROM {measures._relative(a, b)} WHERE tbl = '{t}'" for t, a, b in CLAIMS) + ")")
def w26_claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    cells = published.cells(spark)
    out = None
    for tbl, a, b in CLAIMS:
        one = measures.metrics.relative(cells.filter(F.col("tbl") == tbl), a, b).select("tbl", F.lit(a).alias("base_model"), F.lit(b).alias("new_model"), "subset", "metric", F.round("gain", 1).alias("gain"))
        out = one if out is None else out.unionAll(one)
    return out


@query("w27_volume", "SELECT count(*) AS n, sum(token)::BIGINT AS token_sum, round(sum(scaled), 4) AS scaled_sum, count(*) FILTER (WHERE top <= 0) AS degenerate FROM (SELECT round(greatest(-4.0::DOUBLE, least(4.0::DOUBLE, q / 10 - 2)))::INT + 4 AS token, q / top * 0.6::DOUBLE AS scaled, top FROM (SELECT l_quantity AS q, max(l_quantity) OVER (PARTITION BY l_orderkey) AS top FROM lineitem))")
def w27_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rehearsal of volume: packed order lines as samples, scaled to their peak and quantised, one shuffle."""
    packed = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_quantity"))).alias("s")).select("l_orderkey", F.transform("s", lambda x: x["l_quantity"]).alias("samples"))
    digits = fsq.bounded_round(F.transform("samples", lambda q: q / 10 - 2), 4)
    scaled = signal.normalize_volume(packed.withColumn("digits", digits))
    total = lambda a, z: F.aggregate(a, F.lit(z), lambda s, x: s + x)
    sums = scaled.select(F.size("samples").cast("long").alias("n"), F.aggregate("digits", F.lit(0).cast("long"), lambda s, d: s + d + 4).alias("t"), total(F.col("samples"), 0.0).alias("v"), "vol_degenerate")
    return sums.agg(F.sum("n").alias("n"), F.sum("t").alias("token_sum"), F.round(F.sum("v"), 4).alias("scaled_sum"), F.count_if("vol_degenerate").alias("degenerate"))


def _transfer_sql(name: str, where: str) -> str:
    fit = f"SELECT ctx, c, count(*) AS n FROM cx WHERE {where} GROUP BY 1, 2"
    return f"SELECT '{name}' AS fitted_on, count(*) AS n, round(exp(-avg(ln((coalesce(k.n, 0) + 1.0::DOUBLE) / (coalesce(t.n, 0) + 64.0::DOUBLE)))), 4) AS perplexity FROM (SELECT * FROM cx WHERE lang = 'es') x LEFT JOIN ({fit}) k USING (ctx, c) LEFT JOIN (SELECT ctx, sum(n) AS n FROM ({fit}) GROUP BY ctx) t USING (ctx)"


@query("w28_transfer", corpus_sets.CCTX + " " + " UNION ALL ".join(_transfer_sql(n, w) for n, w in (("others", "lang <> 'es'"), ("all", "true"), ("itself", "lang = 'es'"))))
def w28_transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Perplexity of a language's letters under pair counts of the other languages, of all, and of itself."""
    es = F.col("lang") == "es"
    subsets = {"others": ~es, "all": F.lit(True), "itself": es}
    return _r(policy.nested_perplexity(load(spark, sf_dir, "documents"), corpus_sets.letters(), subsets, 64, scored=es).withColumnRenamed("subset", "fitted_on"), 4)


query("w29_spread", rewards.SPREAD)(rewards.c14_spread)
query("w30_stages", "SELECT * FROM (VALUES ('pretraining', NULL, 'base, phones, text forms'), ('post_training', 'pretraining', 'reward tasks'), ('continual_pretraining', 'post_training', 'instructions, languages'), ('speaker_fine_tuning', 'continual_pretraining', 'target speakers, masked prompts')) AS t(stage, after, inputs)")(lambda spark, sf_dir: mixture.stages(spark))


@query("k5_renderer", "SELECT vec_id, nfe::INT AS nfe, round(pow(1 - 1 / nfe::DOUBLE, nfe), 6) AS left_over FROM (SELECT vec_id FROM embeddings), (VALUES (1), (4), (32)) AS n(nfe)")
def k5_renderer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of the way that is left after N Euler steps from a zero vector to the embedding."""
    rows = load(spark, sf_dir, "embeddings").withColumn("zero", F.transform("embedding", lambda x: x * 0))
    out = None
    for nfe in (1, 4, 32):
        at = surrogate.flow_integrate(F.col("zero"), F.col("embedding"), nfe)
        gap = F.sqrt(surrogate.flow_loss(at, F.col("embedding")) / surrogate.flow_loss(F.col("zero"), F.col("embedding")))
        one = rows.select("vec_id", F.lit(nfe).alias("nfe"), F.round(gap, 6).alias("left_over"))
        out = one if out is None else out.unionAll(one)
    return out
