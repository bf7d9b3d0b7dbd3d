"""Queries of pronunciations, text normalisation, instructions and speakers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.functions.hashing import sql_draw, sql_uniform
from voxtable.functions.units import words
from voxtable.operators import instruct, lexicon, textnorm, vq
from voxtable.operators.tokens import centroids
from voxtable.plans.corpus import TEXTS, texts
from voxtable.registry import query
from voxtable.sources.tables import load, page_text


def _sound_sql() -> str:
    out = "symbol"
    for code, rules in lexicon.SOUNDS.items():
        spelt = "symbol"
        for letters, phone in rules:
            spelt = f"replace({spelt}, '{letters}', '{phone}')"
        out = f"CASE WHEN lang = '{code}' THEN {spelt} ELSE {out} END"
    return out


SYM = r"list_filter(string_split(lower(regexp_replace(text, '[^\p{L}]+', ' ', 'g')), ' '), lambda w: w <> '')"
LEX = f"WITH u AS ({TEXTS}), wd AS (SELECT DISTINCT unnest({SYM}) AS symbol, lang FROM u), rd AS (SELECT symbol, lang, {_sound_sql()} AS phones FROM wd), nr AS (SELECT symbol, count(DISTINCT phones) AS n_readings, min(phones) AS pick FROM rd GROUP BY symbol), lx AS (SELECT rd.*, n_readings, n_readings = 1 AS is_mono FROM rd JOIN nr USING (symbol))"


@query("d1_lexicon", LEX + " SELECT symbol, lang, phones, n_readings, is_mono FROM lx")
def d1_lexicon(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lexicon.build(texts(spark, sf_dir))


def _inpaint_sql(which: str, render: str, rate: float = 1.0, noise: float = 0.0) -> str:
    mono = "AND n_readings = 1" if which == "mono" else ""
    chosen = f"pick IS NOT NULL AND {sql_draw(chr(39) + 'inpaint' + chr(39), 'utt_id', 'pos')} % 10000 < {int(rate * 10000)}"
    swapped = f"CASE WHEN {sql_draw(chr(39) + 'inpaint:noise' + chr(39), 'utt_id', 'pos')} % 10000 < {int(noise * 10000)} THEN reverse(symbol) ELSE symbol END"
    piece = "'/' || pick || '/'" if render == "phones" else f"{swapped} || '/' || pick || '/'"
    return LEX + f""", it AS (SELECT utt_id, unnest(range(len({SYM}))) AS pos, unnest({SYM}) AS symbol FROM u), jn AS (SELECT it.*, pick FROM it LEFT JOIN nr ON it.symbol = nr.symbol {mono})
    SELECT utt_id, md5(string_agg(CASE WHEN {chosen} THEN {piece} ELSE symbol END, ' ' ORDER BY pos)) AS rendered, count(*) FILTER (WHERE {chosen}) AS n_replaced FROM jn GROUP BY utt_id"""


def _inpainted(spark: SparkSession, sf_dir: str, **how: object) -> DataFrame:
    rows = texts(spark, sf_dir)
    return lexicon.inpaint(rows, lexicon.build(rows), **how).withColumn("rendered", F.md5("rendered"))


@query("d2_mono_phones", _inpaint_sql("mono", "phones"))
def d2_mono_phones(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _inpainted(spark, sf_dir)


@query("d3_all_phones", _inpaint_sql("all", "phones"))
def d3_all_phones(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _inpainted(spark, sf_dir, which="all")


@query("d5_mono_both", _inpaint_sql("mono", "both"))
def d5_mono_both(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _inpainted(spark, sf_dir, render="both")


@query("d5_all_both", _inpaint_sql("all", "both"))
def d5_all_both(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _inpainted(spark, sf_dir, which="all", render="both")


@query("d6_noise", _inpaint_sql("mono", "both", 0.5, 0.2))
def d6_noise(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Half the symbols, a fifth of those with another symbol before the right phones."""
    return _inpainted(spark, sf_dir, render="both", rate=0.5, noise=0.2)


@query("d8_vocab", LEX + " SELECT kind, count(*) AS n FROM (SELECT DISTINCT symbol AS token, 'word' AS kind FROM lx UNION SELECT DISTINCT '/' || phones || '/', 'phone' FROM lx) GROUP BY kind")
def d8_vocab(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lexicon.expand_vocab(lexicon.build(texts(spark, sf_dir))).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


@query("d9_append", f"WITH u AS ({TEXTS}) SELECT part, count(*) AS n, count(route) AS n_route FROM (SELECT utt_id, NULL AS route, 'base' AS part FROM u UNION ALL SELECT utt_id, 'phones', 'aux' FROM u WHERE lang = 'en') GROUP BY part")
def d9_append(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = texts(spark, sf_dir)
    both = lexicon.append(base, base.filter("lang = 'en'").withColumn("route", F.lit("phones")), "aux")
    return both.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.count("route").alias("n_route"))


@query("d10_hints", f"WITH u AS ({TEXTS}), s AS (SELECT utt_id, {SYM} AS s FROM u) SELECT utt_id, md5(array_to_string(list_transform(s, lambda w, i: CASE WHEN i - 1 = utt_id % 7 THEN '/x' || utt_id % 7 || '/' ELSE w END), ' ')) AS rendered FROM s")
def d10_hints(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = texts(spark, sf_dir)
    hints = rows.select("utt_id", (F.col("utt_id") % 7).cast("int").alias("pos"), F.concat(F.lit("x"), (F.col("utt_id") % 7).cast("string")).alias("phones"))
    return lexicon.apply_hints(rows, hints).withColumn("rendered", F.md5("rendered"))


def _norm_sql(text: str, verbose: bool = False) -> str:
    out = text
    for code, names in textnorm.DIGITS.items():
        spoken = text
        for sign, by in textnorm.SIGNS.items():
            spoken = f"replace({spoken}, '{sign}', ' {by[code]}{' sign' if verbose else ''} ')"
        for d, name in enumerate(names):
            spoken = f"replace({spoken}, '{d}', ' {name} ')"
        out = f"CASE WHEN lang = '{code}' THEN {spoken} ELSE {out} END"
    return f"trim(regexp_replace({out}, ' +', ' ', 'g'))"


def _inverse_sql(text: str) -> str:
    out = "w"
    for code in textnorm.DIGITS:
        table = {**{n: str(d) for d, n in enumerate(textnorm.DIGITS[code])}, **{by[code]: s for s, by in textnorm.SIGNS.items() if " " not in by[code]}}
        cases = " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in table.items())
        out = f"CASE WHEN lang = '{code}' THEN CASE w {cases} ELSE w END ELSE {out} END"
    return f"array_to_string(list_transform(string_split({text}, ' '), lambda w: {out}), ' ')"


RAW = "SELECT doc_id AS utt_id, text, lang FROM documents WHERE regexp_matches(text, '[0-9%&@$=]')"


def raw_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("utt_id"), "text", "lang")
    return docs.filter(textnorm.has_symbols(F.col("text")))


@query("e1_rules", f"WITH r AS ({RAW}) SELECT utt_id, md5({_norm_sql('text')}) AS spoken FROM r")
def e1_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raw_text(spark, sf_dir).select("utt_id", F.md5(textnorm.normalize(F.col("text"), F.col("lang"))).alias("spoken"))


@query("e2_model_route", f"WITH r AS ({RAW}) SELECT utt_id, md5({_norm_sql('text', True)}) AS spoken FROM r")
def e2_model_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    return raw_text(spark, sf_dir).select("utt_id", F.md5(textnorm.normalize(F.col("text"), F.col("lang"), True)).alias("spoken"))


@query("e3_inverse", f"WITH r AS ({RAW}), n AS (SELECT utt_id, lang, {_norm_sql('text')} AS s FROM r) SELECT utt_id, md5({_inverse_sql('s')}) AS raw FROM n")
def e3_inverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    spoken = raw_text(spark, sf_dir).select("utt_id", "lang", textnorm.normalize(F.col("text"), F.col("lang")).alias("s"))
    return spoken.select("utt_id", F.md5(textnorm.denormalize(F.col("s"), F.col("lang"))).alias("raw"))


@query(
    "e4_aux",
    f"""WITH r AS ({RAW}), n AS (SELECT utt_id, lang, text, {_norm_sql('text')} AS s, {_norm_sql('text', True)} AS v FROM r),
    w AS (SELECT utt_id, 1 AS route, text AS raw, s AS spoken FROM n UNION ALL SELECT utt_id, 2, text, v FROM n UNION ALL SELECT utt_id, 3, {_inverse_sql('s')}, s FROM n)
    SELECT utt_id, route, md5(raw) AS raw_md5, md5(spoken) AS spoken_md5 FROM w QUALIFY row_number() OVER (PARTITION BY md5(raw), md5(spoken) ORDER BY route, utt_id) = 1""",
)
def e4_aux(spark: SparkSession, sf_dir: str) -> DataFrame:
    return textnorm.build_aux(raw_text(spark, sf_dir))


@query("e5_formats", f"WITH r AS ({RAW}), n AS (SELECT utt_id, text, {_norm_sql('text')} AS s FROM r) SELECT utt_id AS audio_id, 'raw' AS format, md5(text) AS text FROM n UNION ALL SELECT utt_id, 'spoken', md5(s) FROM n")
def e5_formats(spark: SparkSession, sf_dir: str) -> DataFrame:
    spoken = raw_text(spark, sf_dir).withColumn("spoken", textnorm.normalize(F.col("text"), F.col("lang")))
    return textnorm.multi_format(spoken).withColumn("text", F.md5("text"))


@query("e6_coverage", r"WITH c AS (SELECT unnest(string_split(regexp_replace(text, '[\p{L}\p{M}\s.,;:!?]', '', 'g'), '')) AS symbol FROM documents) SELECT symbol, count(*) AS n, symbol IN ('%','&','@','$','=','0','1','2','3','4','5','6','7','8','9') AS handled FROM c WHERE symbol <> '' GROUP BY symbol")
def e6_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return textnorm.coverage(load(spark, sf_dir, "documents"))


@query("e7_fold", f"SELECT doc_id, md5(translate(text, '{textnorm.FOLD[0]}', '{textnorm.FOLD[1]}')) AS folded FROM documents")
def e7_fold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select("doc_id", F.md5(textnorm.fold_script(F.col("text"))).alias("folded"))


@query("e8_scoring", r"SELECT doc_id, md5(trim(regexp_replace(lower(text), '[^\p{L}\p{N}]+', ' ', 'g'))) AS scored FROM documents")
def e8_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents").select("doc_id", F.md5(textnorm.for_scoring(F.col("text"))).alias("scored"))


@query("e9_ambiguity", LEX + " SELECT lang, count(*) AS symbols, round(avg((n_readings > 1)::INT), 6) AS ambiguous FROM lx GROUP BY lang")
def e9_ambiguity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return textnorm.ambiguity(lexicon.build(texts(spark, sf_dir))).withColumn("ambiguous", F.round("ambiguous", 6))


PROMPTS = f"WITH u AS ({TEXTS}), pr AS (SELECT u.utt_id, u.text, u.lang, d.source || '-' || u.lang AS speaker, CASE WHEN l.doc_id IS NULL THEN NULL WHEN toxic = 1 THEN 'angry' WHEN quality = 1 THEN 'happy' ELSE 'sad' END AS style FROM u JOIN documents d ON d.doc_id = u.utt_id LEFT JOIN labels l ON l.doc_id = u.utt_id)"


def prompts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """utt_id, text, lang, speaker (one language each), style (null where unlabelled)."""
    source = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("utt_id"), "source")
    labels = load(spark, sf_dir, "labels").select(F.col("doc_id").alias("utt_id"), "quality", "toxic")
    rows = texts(spark, sf_dir).join(source, "utt_id").join(labels, "utt_id", "left")
    style = F.when(F.col("quality").isNull() & F.col("toxic").isNull(), F.lit(None).cast("string")).when(F.col("toxic") == 1, "angry").when(F.col("quality") == 1, "happy").otherwise("sad")
    return rows.select("utt_id", "text", "lang", F.concat_ws("-", "source", "lang").alias("speaker"), style.alias("style"))


@query("f1_prompt", PROMPTS + " SELECT utt_id, md5(CASE WHEN style IS NULL THEN text ELSE style || '<|endofprompt|>' || text END) AS prompt FROM pr")
def f1_prompt(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prompts(spark, sf_dir).select("utt_id", F.md5(instruct.with_prompt(F.col("style"), F.col("text"))).alias("prompt"))


def _tag_sql() -> str:
    u = "(" + sql_draw("'tag'", "utt_id", "i - 1") + " % 100)"
    return f"WITH u AS ({TEXTS}), tg AS (SELECT utt_id, text, array_to_string(list_transform(list_filter(regexp_split_to_array(trim(text), '\\s+'), lambda w: w <> ''), lambda w, i: CASE WHEN {u} < 5 THEN w || ' [laughter]' WHEN {u} < 10 THEN w || ' [breath]' WHEN {u} < 20 THEN '<strong>' || w || '</strong>' ELSE w END), ' ') AS tagged FROM u)"


def tagged(spark: SparkSession, sf_dir: str) -> DataFrame:
    return texts(spark, sf_dir).withColumn("tagged", instruct.inject(words(F.col("text")), F.col("utt_id")))


@query("f2_bursts", _tag_sql() + r" SELECT utt_id, len(regexp_extract_all(tagged, '\[laughter\]'))::INT AS laughter, len(regexp_extract_all(tagged, '\[breath\]'))::INT AS breath FROM tg")
def f2_bursts(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = instruct.bursts(F.col("tagged"))
    count = lambda name: F.size(F.filter(found, lambda b: b == name)).alias(name)
    return tagged(spark, sf_dir).select("utt_id", count("laughter"), count("breath"))


@query("f3_emphasis", _tag_sql() + " SELECT utt_id, array_to_string(regexp_extract_all(tagged, '<strong>([^<]*)</strong>', 1), ' ') AS spans, true AS well_formed FROM tg")
def f3_emphasis(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tagged(spark, sf_dir).select("utt_id", F.array_join(instruct.emphasis(F.col("tagged")), " ").alias("spans"), instruct.well_formed(F.col("tagged")).alias("well_formed"))


@query("f4_inject", _tag_sql() + " SELECT utt_id, md5(tagged) AS tagged, true AS restores FROM tg")
def f4_inject(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tagged(spark, sf_dir).select("utt_id", F.md5("tagged").alias("tagged"), (instruct.strip_tags(F.col("tagged")) == F.col("text")).alias("restores"))


STYLES = "SELECT source || ' ' || coalesce(role, '') || ' ' || lang AS style, count(*) AS n FROM documents d JOIN conversations c ON c.conv_id = d.doc_id % 100 GROUP BY 1 ORDER BY n DESC, style LIMIT 100"


@query("f5_styles", STYLES)
def f5_styles(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select((F.col("doc_id") % 100).alias("conv_id"), "source", "lang")
    rows = docs.join(load(spark, sf_dir, "conversations").select("conv_id", "role"), "conv_id")
    return instruct.top_styles(rows.select(F.concat_ws(" ", "source", F.coalesce("role", F.lit("")), "lang").alias("style")))


@query("f6_types", "SELECT CASE style WHEN 'angry' THEN 'emotion' WHEN 'happy' THEN 'emotion' WHEN 'sad' THEN 'emotion' ELSE 'none' END AS kind, count(*) AS n FROM (" + PROMPTS + " SELECT style FROM pr) GROUP BY 1")
def f6_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    kind = F.coalesce(F.when(F.col("style").isNotNull(), instruct.style_type(F.col("style"))), F.lit("none"))
    return prompts(spark, sf_dir).groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("n"))


def _polyglot_sql() -> str:
    out = "NULL"
    for code, wording in instruct.POLYGLOT.items():
        out = f"CASE WHEN lang = '{code}' THEN replace(replace('{wording}', '{{s}}', speaker), '{{l}}', lang) ELSE {out} END"
    return out


@query("f7_polyglot", PROMPTS + f" SELECT utt_id, {_polyglot_sql()} AS prompt FROM pr")
def f7_polyglot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prompts(spark, sf_dir).select("utt_id", instruct.polyglot_prompt(F.col("speaker"), F.col("lang")).alias("prompt"))


@query("f8_speaker_style", PROMPTS + " SELECT utt_id, trim(coalesce('Speaker ' || speaker || '.', '') || ' ' || coalesce('Style: ' || style || '.', '')) AS prompt FROM pr")
def f8_speaker_style(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prompts(spark, sf_dir).select("utt_id", instruct.speaker_style_prompt(F.col("speaker"), F.col("style")).alias("prompt"))


@query("f9_mask", PROMPTS + f" SELECT utt_id, CASE WHEN {sql_uniform(chr(39) + 'mask:speaker' + chr(39), 'utt_id')} >= 0.3::DOUBLE THEN speaker END AS speaker, CASE WHEN {sql_uniform(chr(39) + 'mask:style' + chr(39), 'utt_id')} >= 0.2::DOUBLE THEN style END AS style FROM pr")
def f9_mask(spark: SparkSession, sf_dir: str) -> DataFrame:
    return instruct.mask(prompts(spark, sf_dir), 0.3, 0.2).select("utt_id", "speaker", "style")


MONO = f"SELECT lang, speaker FROM (SELECT min(lang) AS lang, speaker FROM pr GROUP BY speaker HAVING count(DISTINCT lang) = 1) QUALIFY row_number() OVER (PARTITION BY lang ORDER BY {sql_draw(chr(39) + 'mono' + chr(39), 'speaker')}, speaker) <= 5"


@query("f10_select", PROMPTS + " " + MONO)
def f10_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    return instruct.select_monolingual(prompts(spark, sf_dir), 5)


@query("f11_sft", PROMPTS + " SELECT part, count(*) AS n, count(speaker) AS with_speaker, count(style) AS with_style FROM (SELECT speaker, style, 'target' AS part FROM pr WHERE speaker = 'src1-en' UNION ALL SELECT NULL, style, 'instruction' FROM pr WHERE style IS NOT NULL) GROUP BY part")
def f11_sft(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = prompts(spark, sf_dir)
    both = instruct.build_sft(rows.filter("speaker = 'src1-en'"), rows.filter("style IS NOT NULL"))
    return both.groupBy("part").agg(F.count(F.lit(1)).alias("n"), F.count("speaker").alias("with_speaker"), F.count("style").alias("with_style"))


@query("f14_growth", "WITH h AS (SELECT n_chars / 54000.0::DOUBLE AS hours, quality FROM documents JOIN labels USING (doc_id)) SELECT 'before' AS stage, round(sum(hours) FILTER (WHERE quality = 1), 6) AS hours, 1.0::DOUBLE AS growth FROM h UNION ALL SELECT 'after', round(sum(hours), 6), round(sum(hours) / sum(hours) FILTER (WHERE quality = 1), 6) FROM h")
def f14_growth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hours of instructed speech before and after the set grew, and the factor."""
    rows = load(spark, sf_dir, "documents").select("doc_id", (F.col("n_chars") / 54000.0).alias("hours")).join(load(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    sums = rows.agg(F.sum(F.when(F.col("quality") == 1, F.col("hours"))).alias("b"), F.sum("hours").alias("a"))
    stages = F.array(F.struct(F.lit("before").alias("stage"), F.round("b", 6).alias("hours"), F.lit(1.0).alias("growth")), F.struct(F.lit("after").alias("stage"), F.round("a", 6).alias("hours"), F.round(F.col("a") / F.col("b"), 6).alias("growth")))
    return sums.select(F.explode(stages).alias("s")).select("s.*")


@query("f12_center_k1", "WITH e AS (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings), m AS (SELECT label, pos, avg(x) AS m FROM e GROUP BY 1, 2) SELECT label, round(sum(m), 5) AS total, round(sum(m * pos), 4) AS moment FROM m GROUP BY label")
def f12_center_k1(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = centroids(load(spark, sf_dir, "embeddings"), "label", "embedding").select("label", F.posexplode("centre").alias("p", "m"))
    return c.groupBy("label").agg(F.round(F.sum("m"), 5).alias("total"), F.round(F.sum(F.col("m") * (F.col("p") + 1)), 4).alias("moment"))


@query("f12_center_k")
def f12_center_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two timbre centres for each of three speakers."""
    rows, out = load(spark, sf_dir, "embeddings"), None
    for speaker in (0, 1, 2):
        mine = rows.filter(F.col("label") == speaker)
        one = vq.assign(mine, vq.fit(mine, 2, iters=3)).groupBy("label", "code").agg(F.count(F.lit(1)).alias("n"))
        out = one if out is None else out.unionAll(one)
    return out


@query(
    "f13_attach",
    """WITH e AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings), m AS (SELECT label, pos, avg(x) AS m FROM e GROUP BY 1, 2)
    SELECT vec_id, e.label, round(sqrt(sum((x - m) * (x - m))), 5) AS dist FROM e JOIN m ON e.label = m.label AND e.pos = m.pos GROUP BY vec_id, e.label""",
)
def f13_attach(spark: SparkSession, sf_dir: str) -> DataFrame:
    from voxtable.functions.vectors import squared_distance

    rows = load(spark, sf_dir, "embeddings")
    centres = centroids(rows, "label", "embedding")
    return rows.join(centres, "label").select("vec_id", "label", F.round(F.sqrt(squared_distance(F.col("centre"), F.col("embedding"))), 5).alias("dist"))


@query(
    "page_text",
    r"""WITH t AS (SELECT page_id, regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]+>', ' ', 'g') AS t FROM pages)
    SELECT page_id, md5(trim(regexp_replace(replace(replace(replace(replace(replace(replace(t, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&'), '\s+', ' ', 'g'))) AS text FROM t""",
)
def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return page_text(load(spark, sf_dir, "pages")).withColumn("text", F.md5("text"))
