"""Queries of the quantisers, token streams and probes."""

from __future__ import annotations

from hashlib import md5

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.operators import fsq, signal, tokens, vq
from voxtable.registry import query
from voxtable.sources.tables import load

SPEC = fsq.FsqSpec()


def _sql_matrix(rows: list[list[float]]) -> str:
    return "[" + ", ".join("[" + ", ".join(f"{v!r}::DOUBLE" for v in r) + "]" for r in rows) + "]"


def _dot(a: str, b: str) -> str:
    return f"list_reduce(list_transform(list_zip({a}, {b}), lambda p: p[1]::DOUBLE * p[2]::DOUBLE), lambda s, x: s + x, 0.0::DOUBLE)"


def sql_codes(spec: fsq.FsqSpec) -> str:
    part = f"embedding[{spec.first + 1}:{spec.first + spec.width}]"
    return f"list_transform({_sql_matrix(spec.down())}, lambda r: round({_dot('r', part)}, 6))"


def sql_digits(spec: fsq.FsqSpec) -> str:
    k = spec.k
    value = f"round(tanh(v) * {k})" if spec.bound == "tanh" else f"round(greatest(-{k}.0::DOUBLE, least({k}.0::DOUBLE, v)))"
    return f"list_transform({sql_codes(spec)}, lambda v: {value}::INT)"


def sql_token(spec: fsq.FsqSpec, digits: str = "digits") -> str:
    add = spec.k if spec.offset == "shifted" else 0
    return " + ".join(f"({digits}[{j + 1}] + {add}) * {spec.radix**j}::BIGINT" for j in range(spec.digits))


def tok_sql(spec: fsq.FsqSpec) -> str:
    return f"SELECT vec_id, label, embedding, digits, {sql_token(spec)} AS token FROM (SELECT *, {sql_digits(spec)} AS digits FROM embeddings)"


def emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings")


def _tok(spark: SparkSession, sf_dir: str, spec: fsq.FsqSpec = SPEC) -> DataFrame:
    return fsq.tokenize(emb(spark, sf_dir), spec)


def _joined(col: F.Column) -> F.Column:
    return F.array_join(F.transform(col, lambda x: x.cast("string")), ",")


@query("b1_project", f"SELECT vec_id, c[1] AS c0, c[2] AS c1, c[3] AS c2, c[4] AS c3 FROM (SELECT vec_id, {sql_codes(SPEC)} AS c FROM embeddings)")
def b1_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = emb(spark, sf_dir).select("vec_id", fsq.codes(F.col("embedding"), SPEC).alias("c"))
    return c.select("vec_id", *[F.col("c")[j].alias(f"c{j}") for j in range(4)])


@query("b2_round", f"SELECT vec_id, array_to_string({sql_digits(SPEC)}, ',') AS digits FROM embeddings")
def b2_round(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tok(spark, sf_dir).select("vec_id", _joined(F.col("digits")).alias("digits"))


TANH = fsq.FsqSpec(digits=6, k=1, gain=8.0, bound="tanh")


@query("b2_round_tanh", f"SELECT vec_id, array_to_string({sql_digits(TANH)}, ',') AS digits FROM embeddings")
def b2_round_tanh(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tok(spark, sf_dir, TANH).select("vec_id", _joined(F.col("digits")).alias("digits"))


PRINTED = fsq.FsqSpec(offset="printed")


@query("b3_encode", f"SELECT vec_id, {sql_token(SPEC)} AS shifted, {sql_token(PRINTED)} AS printed FROM (SELECT *, {sql_digits(SPEC)} AS digits FROM embeddings)")
def b3_encode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tok(spark, sf_dir).select("vec_id", F.col("token").alias("shifted"), fsq.encode(F.col("digits"), SPEC.k, "printed").alias("printed"))


@query("b3_decode", f"SELECT vec_id, array_to_string({sql_digits(SPEC)}, ',') AS digits, true AS inverts FROM embeddings")
def b3_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    back = _tok(spark, sf_dir).withColumn("back", fsq.decode(F.col("token"), SPEC.digits, SPEC.k))
    printed = fsq.decode(fsq.encode(F.col("digits"), SPEC.k, "printed"), SPEC.digits, SPEC.k, "printed")
    return back.withColumn("inverts", printed == F.col("back")).select("vec_id", _joined(F.col("back")).alias("digits"), "inverts")


UP = f"list_transform({_sql_matrix(SPEC.up())}, lambda r: {_dot('r', 'digits')})"
MSE = f"({_dot('d', 'd')}) / 64 AS mse FROM (SELECT vec_id, label, digits, list_transform(list_zip(embedding, {UP}), lambda p: p[1]::DOUBLE - p[2]) AS d FROM ({tok_sql(SPEC)}))"


@query("b4_reconstruct", f"SELECT vec_id, round(r[1], 6) AS r0, round(r[64], 6) AS r63 FROM (SELECT vec_id, {UP} AS r FROM ({tok_sql(SPEC)}))")
def b4_reconstruct(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = _tok(spark, sf_dir).select("vec_id", fsq.reconstruct(F.col("digits"), SPEC).alias("r"))
    return r.select("vec_id", F.round(F.col("r")[0], 6).alias("r0"), F.round(F.col("r")[63], 6).alias("r63"))


@query("b5_tokenize", f"SELECT vec_id, token FROM ({tok_sql(SPEC)})")
def b5_tokenize(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _tok(spark, sf_dir).select("vec_id", "token")


@query("b6_pack", f"SELECT vec_id // 10 AS utt_id, string_agg(token::VARCHAR, ',' ORDER BY vec_id % 10) AS tokens, count(*) / 25.0::DOUBLE AS duration_s FROM ({tok_sql(SPEC)}) GROUP BY 1")
def b6_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    timed = _tok(spark, sf_dir).select(F.floor(F.col("vec_id") / 10).alias("utt_id"), (F.col("vec_id") % 10).alias("t"), "token")
    return tokens.pack(timed).select("utt_id", _joined(F.col("tokens")).alias("tokens"), "duration_s")


USAGE = "SELECT sum(c)::BIGINT AS n, count(*) AS used, round(count(*) / {q}.0::DOUBLE, 6) AS share, round(ln(sum(c)) - sum(c * ln(c)) / sum(c), 6) AS entropy, round(exp(ln(sum(c)) - sum(c * ln(c)) / sum(c)), 6) AS perplexity FROM (SELECT token, count(*)::DOUBLE AS c FROM ({tok}) GROUP BY token)"


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


@query("b8_usage", USAGE.format(q=SPEC.codebook_size, tok=tok_sql(SPEC)))
def b8_usage(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(tokens.usage(_tok(spark, sf_dir), SPEC.codebook_size))


@query("b9_mse", f"SELECT round(avg(mse), 6) AS mse, count(*) AS n FROM (SELECT {MSE})")
def b9_mse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(_tok(spark, sf_dir).agg(F.avg(fsq.reconstruction_error(SPEC)).alias("mse"), F.count(F.lit(1)).alias("n")))


SWEEP = [fsq.FsqSpec(digits=d, k=k) for d, k in ((2, 1), (4, 1), (4, 4), (6, 1), (6, 2))]


@query("b10_sweep", " UNION ALL ".join(f"SELECT {s.digits} AS d, {s.k} AS k, u.* FROM ({USAGE.format(q=s.codebook_size, tok=tok_sql(s))}) AS u" for s in SWEEP))
def b10_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = emb(spark, sf_dir)
    out = None
    for s in SWEEP:
        one = _rounded(tokens.usage(fsq.tokenize(rows, s), s.codebook_size)).select(F.lit(s.digits).alias("d"), F.lit(s.k).alias("k"), "*")
        out = one if out is None else out.unionAll(one)
    return out


def literal_book(k: int, width: int = 64, scale: float = 0.15) -> list[list[float]]:
    """A seeded codebook, the same in every engine."""
    value = lambda c, i: scale * (int(md5(f"book|{k}|{c}|{i}".encode()).hexdigest()[:8], 16) / 2**31 - 1)
    return [[round(value(c, i), 6) for i in range(width)] for c in range(k)]


BOOK, BOOK2 = literal_book(16), literal_book(8, scale=0.08)


def _nearest(v: str, book: list[list[float]]) -> str:
    gap = f"list_transform(list_zip(c, {v}), lambda p: p[1] - p[2]::DOUBLE)"
    dist = f"list_reduce(list_transform({gap}, lambda g: g * g), lambda s, x: s + x, 0.0::DOUBLE)"
    return f"list_min(list_transform({_sql_matrix(book)}, lambda c, i: {{'dist': round({dist}, 9), 'id': i - 1}})).id"


@query("b11_vq_assign", f"SELECT vec_id, ({_nearest('embedding', BOOK)})::INT AS code FROM embeddings")
def b11_vq_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vq.assign(emb(spark, sf_dir), BOOK).select("vec_id", "code")


@query("b11_vq_fit")
def b11_vq_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = emb(spark, sf_dir)
    return vq.assign(rows, vq.fit(rows, 8)).groupBy("code").agg(F.count(F.lit(1)).alias("n"))


@query(
    "b12_residual",
    f"""WITH a AS (SELECT vec_id, embedding, ({_nearest('embedding', BOOK)})::INT AS c0 FROM embeddings),
    b AS (SELECT vec_id, c0, list_transform(list_zip(embedding, {_sql_matrix(BOOK)}[c0 + 1]), lambda p: p[1]::DOUBLE - p[2]) AS rest FROM a)
    SELECT vec_id, c0 AS first_stage, c0 || ',' || ({_nearest('rest', BOOK2)})::INT AS codes FROM b""",
)
def b12_residual(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vq.residual(emb(spark, sf_dir), [BOOK, BOOK2]).select("vec_id", F.col("codes")[0].alias("first_stage"), _joined(F.col("codes")).alias("codes"))


@query("b13_cluster")
def b13_cluster(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters of one view of the features, as self-supervised tokens."""
    rows = emb(spark, sf_dir).withColumn("embedding", F.slice("embedding", 33, 32))
    return vq.assign(rows, vq.fit(rows, 8)).groupBy("code").agg(F.count(F.lit(1)).alias("n"))


TASKS = {"lid": "lang", "sentiment": "toxic", "quality": "quality"}


@query(
    "b15_tasks",
    """WITH x AS (SELECT doc_id, n_chars / 54000.0::DOUBLE AS hours, lang, toxic, quality FROM documents LEFT JOIN labels USING (doc_id))
    SELECT task, count(*) AS n, round(sum(hours), 6) AS hours FROM (SELECT 'lid' AS task, lang AS truth, hours FROM x UNION ALL SELECT 'sentiment', toxic::VARCHAR, hours FROM x UNION ALL SELECT 'quality', quality::VARCHAR, hours FROM x) WHERE truth IS NOT NULL GROUP BY task""",
)
def b15_tasks(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "documents").select("doc_id", "lang", (F.col("n_chars") / 54000.0).alias("hours")).join(load(spark, sf_dir, "labels"), "doc_id", "left")
    tagged = tokens.multitask_examples(rows, TASKS, "hours")
    return tagged.groupBy("task").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("hours"), 6).alias("hours"))


@query("b16_probe_token", f"SELECT round(sum(hit) / sum(n)::DOUBLE, 6) AS accuracy, sum(n)::BIGINT AS n FROM (SELECT token, max(n) AS hit, sum(n) AS n FROM (SELECT token, label, count(*) AS n FROM ({tok_sql(SPEC)}) GROUP BY token, label) GROUP BY token)")
def b16_probe_token(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(tokens.majority_probe(_tok(spark, sf_dir), "token", "label"))


@query(
    "b16_probe_centroid",
    """WITH e AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings), m AS (SELECT label, pos, avg(x) AS m FROM e GROUP BY label, pos),
    d AS (SELECT vec_id, e.label, m.label AS guess, round(sum((x - m) * (x - m)), 9) AS dist FROM e JOIN m USING (pos) GROUP BY ALL), b AS (SELECT vec_id, label, guess FROM d QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY dist, guess) = 1)
    SELECT round(avg((label = guess)::INT), 6) AS accuracy, count(*) AS n FROM b""",
)
def b16_probe_centroid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rounded(tokens.centroid_probe(emb(spark, sf_dir), "label", "embedding"))


@query(
    "b17_resample",
    """WITH r AS (SELECT user_id, list(value ORDER BY event_id) AS s FROM events GROUP BY user_id), i AS (SELECT user_id, s, unnest(range(floor(len(s) * 40.0::DOUBLE / 25.0::DOUBLE)::BIGINT)) AS i FROM r),
    v AS (SELECT user_id, i, i * 25.0::DOUBLE / 40.0::DOUBLE AS pos, s FROM i)
    SELECT user_id, round(sum(s[least(floor(pos)::INT, len(s) - 1) + 1] + (pos - floor(pos)) * (s[least(floor(pos)::INT + 1, len(s) - 1) + 1] - s[least(floor(pos)::INT, len(s) - 1) + 1])), 6) AS linear,
    round(sum(s[least(floor(pos + 0.5::DOUBLE)::INT, len(s) - 1) + 1]), 6) AS nearest FROM v GROUP BY user_id""",
)
def b17_resample(spark: SparkSession, sf_dir: str) -> DataFrame:
    seq = load(spark, sf_dir, "events").groupBy("user_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("event_id", "value"))), lambda s: s["value"]).alias("s"))
    total = lambda c: F.round(F.aggregate(c, F.lit(0.0), lambda a, x: a + x), 6)
    return seq.select("user_id", total(signal.resample(F.col("s"), 25, 40)).alias("linear"), total(signal.resample(F.col("s"), 25, 40, "nearest")).alias("nearest"))

