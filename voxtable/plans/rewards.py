"""Queries of policies, relaxed samples, rewards and their optimisation, on event sequences as tokens."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from voxtable.functions.hashing import sql_uniform
from voxtable.operators import dist, policy, reward, tokens
from voxtable.registry import query
from voxtable.sources.tables import load

CODES = ["click", "error", "purchase", "signup", "view"]
N = len(CODES)
ALPHA = 1.0

CTX = "WITH ev AS (SELECT event_id, user_id, event_type, value, coalesce(lag(event_type) OVER (PARTITION BY user_id ORDER BY event_id), '^') AS ctx, least(4, floor(value / 25))::INT AS code FROM events)"
COUNTS = CTX + f", ct AS (SELECT ctx, event_type AS code, count(*) AS n FROM ev GROUP BY 1, 2), lg AS (SELECT ctx, code, n, ln((n + 1.0::DOUBLE) / (sum(n) OVER (PARTITION BY ctx) + {N}.0::DOUBLE)) AS logit FROM ct)"
#: Every context's distribution over all codes, long.
FULL = COUNTS + f""", tot AS (SELECT ctx, sum(n) AS total FROM ct GROUP BY ctx), cd AS (SELECT unnest([{', '.join(f"'{c}'" for c in CODES)}]) AS code, unnest(range({N})) AS k),
 lo AS (SELECT t.ctx, t.total, k, cd.code, ln((coalesce(ct.n, 0) + 1.0::DOUBLE) / (t.total + {N}.0::DOUBLE)) AS x FROM tot t CROSS JOIN cd LEFT JOIN ct ON ct.ctx = t.ctx AND ct.code = cd.code)"""


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "value")
    return policy.contexts(rows, "user_id", ("event_id",), "event_type").withColumn("code", F.least(F.lit(4), F.floor(F.col("value") / 25)).cast("int"))


def counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return policy.from_counts(events(spark, sf_dir), "event_type", N, ALPHA)


def logits(spark: SparkSession, sf_dir: str) -> DataFrame:
    return policy.dense(counts(spark, sf_dir), CODES, ALPHA)


def _long(df: DataFrame, col: str, name: str = "v") -> DataFrame:
    return df.select("ctx", F.posexplode(col).alias("k", name)).select("ctx", "k", F.round(name, 6).alias(name))


@query("c1_policy", COUNTS + " SELECT ctx, code, n, round(logit, 6) AS logit FROM lg")
def c1_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counts(spark, sf_dir).withColumn("logit", F.round("logit", 6))


@query("c2_logsoftmax", FULL + " SELECT ctx, k::INT AS k, round(2 * x - ln(sum(exp(2 * x)) OVER (PARTITION BY ctx)), 6) AS v FROM lo")
def c2_logsoftmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of doubled logits, so that the normaliser has something to do."""
    return _long(logits(spark, sf_dir).withColumn("p", dist.log_softmax(F.transform("logits", lambda x: 2 * x))), "p")


@query("c3_gumbel", f"SELECT event_id, k::INT AS k, round(-ln(-ln({sql_uniform(chr(39) + 'g' + chr(39), 'event_id', 'k')})), 6) AS g FROM events, range({N}) AS r(k)")
def c3_gumbel(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events").select("event_id", F.explode(F.sequence(F.lit(0), F.lit(N - 1))).alias("k"))
    return rows.select("event_id", "k", F.round(dist.gumbel("g", F.col("event_id"), F.col("k")), 6).alias("g"))


def _noisy(spark: SparkSession, sf_dir: str) -> DataFrame:
    noise = F.array(*[dist.gumbel("g", F.col("event_id"), F.lit(k)) for k in range(N)])
    return events(spark, sf_dir).join(F.broadcast(logits(spark, sf_dir)), "ctx").withColumn("noise", noise)


NOISY = FULL + f", no AS (SELECT e.event_id, e.user_id, lo.ctx, k, x - ln(-ln({sql_uniform(chr(39) + 'g' + chr(39), 'e.event_id', 'k')})) AS y FROM ev e JOIN lo USING (ctx))"


@query("c4_relaxed", NOISY + ", w AS (SELECT event_id, k, exp(y / 0.5::DOUBLE) / sum(exp(y / 0.5::DOUBLE)) OVER (PARTITION BY event_id) AS w FROM no) SELECT event_id, round(max(w), 6) AS top, round(sum(w * k), 6) AS mean FROM w GROUP BY event_id")
def c4_relaxed(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = _noisy(spark, sf_dir).withColumn("w", dist.gumbel_softmax(F.col("logits"), F.col("noise"), 0.5))
    mean = dist.expected(F.col("w"), F.array(*[F.lit(float(k)) for k in range(N)]))
    return w.select("event_id", F.round(F.array_max("w"), 6).alias("top"), F.round(mean, 6).alias("mean"))


@query("c4_hard", NOISY + " SELECT event_id, arg_max(k, y)::INT AS sampled FROM no GROUP BY event_id")
def c4_hard(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = dist.gumbel_softmax(F.col("logits"), F.col("noise"), 0.5, "hard")
    return _noisy(spark, sf_dir).select("event_id", (F.array_position(w, F.lit(1.0)) - 1).cast("int").alias("sampled"))


T2T = CTX + f", tt AS (SELECT code, event_type, ln((count(*) + 0.5::DOUBLE) / (sum(count(*)) OVER (PARTITION BY code) + 0.5::DOUBLE * {N})) AS logp FROM ev GROUP BY code, event_type)"


def token2text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reward.fit_token2text(events(spark, sf_dir), "code", "event_type", N)


@query("c5_token2text", T2T + " SELECT code, event_type, round(logp, 6) AS logp FROM tt")
def c5_token2text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token2text(spark, sf_dir).withColumn("logp", F.round("logp", 6))


@query("c6_asr_reward", T2T + " SELECT user_id, round(sum(coalesce(logp, -10)), 4) AS reward FROM ev LEFT JOIN tt USING (code, event_type) GROUP BY user_id")
def c6_asr_reward(spark: SparkSession, sf_dir: str) -> DataFrame:
    return reward.asr(events(spark, sf_dir), F.broadcast(token2text(spark, sf_dir)), "code", "event_type", -10.0, "user_id").withColumn("reward", F.round("reward", 4))


MTR = {"quality": "ln(0.1D + 0.8D * quality)", "safety": "ln(0.9D - 0.8D * toxic)"}


@query("c7_multi_reward", "SELECT doc_id, round(ln(0.1::DOUBLE + 0.8::DOUBLE * quality), 6) AS quality, round(ln(0.9::DOUBLE - 0.8::DOUBLE * toxic), 6) AS safety, round(ln(0.1::DOUBLE + 0.8::DOUBLE * quality) + 2 * ln(0.9::DOUBLE - 0.8::DOUBLE * toxic), 6) AS reward FROM labels")
def c7_multi_reward(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = reward.multi(load(spark, sf_dir, "labels"), MTR, {"safety": 2.0})
    return r.select("doc_id", F.round(F.col("rewards")["quality"], 6).alias("quality"), F.round(F.col("rewards")["safety"], 6).alias("safety"), F.round("reward", 6).alias("reward"))


@query("c7a_emotion_only", "SELECT doc_id, round(ln(0.1::DOUBLE + 0.8::DOUBLE * quality), 6) AS reward FROM labels")
def c7a_emotion_only(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The variant with one task."""
    return reward.multi(load(spark, sf_dir, "labels"), {"emotion": MTR["quality"]}).select("doc_id", F.round("reward", 6).alias("reward"))


@query(
    "c7b_speaker_task",
    """WITH e AS (SELECT vec_id, label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings), m AS (SELECT label, pos, avg(x) AS m FROM e GROUP BY 1, 2),
    s AS (SELECT vec_id, e.label, sum(x * m) / (sqrt(sum(x * x)) * sqrt(sum(m * m))) AS c FROM e JOIN m ON e.label = m.label AND e.pos = m.pos GROUP BY 1, 2) SELECT vec_id, round(ln((1 + c) / 2), 5) AS speaker, round(ln((1 + c) / 2) + ln(CASE WHEN label % 2 = 0 THEN 0.9::DOUBLE ELSE 0.1::DOUBLE END), 5) AS reward FROM s""",
)
def c7b_speaker_task(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearness to the speaker's centre as one more task, beside another attribute's posterior."""
    from voxtable.functions.vectors import cosine

    rows = load(spark, sf_dir, "embeddings")
    near = rows.join(tokens.centroids(rows, "label", "embedding"), "label").withColumn("c", cosine(F.col("embedding"), F.col("centre")))
    r = reward.multi(near, {"speaker": "ln((1 + c) / 2)", "other": "ln(CASE WHEN label % 2 = 0 THEN 0.9D ELSE 0.1D END)"})
    return r.select("vec_id", F.round(F.col("rewards")["speaker"], 5).alias("speaker"), F.round("reward", 5).alias("reward"))


@query("c8_token_kl", FULL + ", p AS (SELECT ctx, k, exp(2 * x) / sum(exp(2 * x)) OVER (PARTITION BY ctx) AS p, exp(x) / sum(exp(x)) OVER (PARTITION BY ctx) AS q FROM lo) SELECT ctx, round(sum(p * ln(p / q)), 6) AS kl FROM p GROUP BY ctx")
def c8_token_kl(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Divergence of the sharpened policy from the policy itself, by context."""
    kl = dist.token_kl(dist.softmax(F.transform("logits", lambda x: 2 * x)), dist.softmax(F.col("logits")))
    return logits(spark, sf_dir).select("ctx", F.round(kl, 6).alias("kl"))


@query("c8_seq_kl", FULL + ", p AS (SELECT ctx, code, ln(exp(2 * x) / sum(exp(2 * x)) OVER (PARTITION BY ctx)) - ln(exp(x) / sum(exp(x)) OVER (PARTITION BY ctx)) AS r FROM lo) SELECT user_id, round(sum(r), 4) AS kl FROM ev JOIN p ON p.ctx = ev.ctx AND p.code = ev.event_type GROUP BY user_id")
def c8_seq_kl(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sequence-level estimate: log ratio of each observed sequence."""
    ratio = F.zip_with(dist.log_softmax(F.transform("logits", lambda x: 2 * x)), dist.log_softmax(F.col("logits")), lambda a, b: a - b)
    table = logits(spark, sf_dir).select("ctx", F.posexplode(ratio).alias("k", "r")).withColumn("event_type", F.element_at(F.array(*map(F.lit, CODES)), F.col("k") + 1))
    return events(spark, sf_dir).join(F.broadcast(table), ["ctx", "event_type"]).groupBy("user_id").agg(F.round(F.sum("r"), 4).alias("kl"))


VALUES = [0.2, -1.0, 1.0, 0.5, 0.0]
_VALUES = "[" + ", ".join(f"{v}::DOUBLE" for v in VALUES) + "]"


def start(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Policy table for the optimiser: the reference is where it starts; each code has a fixed reward."""
    return logits(spark, sf_dir).select("ctx", F.col("total").alias("n"), "logits", F.col("logits").alias("ref"), F.array(*map(F.lit, VALUES)).alias("values"))


@query("c9_objective", FULL + f""", p AS (SELECT ctx, k, total, exp(2 * x) / sum(exp(2 * x)) OVER (PARTITION BY ctx) AS p, exp(x) / sum(exp(x)) OVER (PARTITION BY ctx) AS q FROM lo),
  c AS (SELECT ctx, any_value(total) AS n, sum(p * ({_VALUES})[k + 1]) AS r, sum(p * ln(p / q)) AS d FROM p GROUP BY ctx)
  SELECT round(sum(r * n) / sum(n), 6) AS reward, round(sum(d * n) / sum(n), 6) AS kl, round(sum(r * n) / sum(n) - 0.1::DOUBLE * sum(d * n) / sum(n), 6) AS objective FROM c""")
def c9_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    sharp = start(spark, sf_dir).withColumn("logits", F.transform("logits", lambda x: 2 * x))
    return reward.objective(sharp, 0.1).select(*[F.round(c, 6).alias(c) for c in ("reward", "kl", "objective")])


@query("c10_optimize")
def c10_optimize(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, trace = reward.optimize(start(spark, sf_dir), reward.Settings())
    return reward.trace_frame(spark, trace)


@query("c11_reinforce")
def c11_reinforce(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, trace = reward.optimize(start(spark, sf_dir), reward.Settings(), score_function=True)
    return reward.trace_frame(spark, trace)


@query("c12_no_divergence")
def c12_no_divergence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """End of the optimisation for a sweep of beta and tau."""
    rows = []
    for beta in (0.0, 0.1, 1.0):
        for tau in (0.5, 1.0):
            _, trace = reward.optimize(start(spark, sf_dir), reward.Settings(iters=5, beta=beta, tau=tau))
            rows.append({"beta": beta, "tau": tau, **trace[-1]})
    return reward.trace_frame(spark, rows)


@query(
    "c13_side_effects",
    """WITH a AS (SELECT event_type AS metric, avg(value) AS v FROM events WHERE event_id % 2 = 0 AND event_type <> 'view' GROUP BY 1), b AS (SELECT event_type AS metric, avg(value) AS v FROM events WHERE event_id % 2 = 1 AND event_type <> 'click' GROUP BY 1)
    SELECT metric, round(a.v, 6) AS before, round(b.v, 6) AS after, round(b.v - a.v, 6) AS delta FROM a FULL JOIN b USING (metric)""",
)
def c13_side_effects(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events")
    side = lambda odd, without: rows.filter((F.col("event_id") % 2 == odd) & (F.col("event_type") != without)).groupBy(F.col("event_type").alias("metric")).agg(F.avg("value").alias("value"))
    both = reward.side_effects(side(0, "view"), side(1, "click"))
    return both.select("metric", *[F.round(c, 6).alias(c) for c in ("before", "after", "delta")])


SPREAD = "WITH m AS (SELECT user_id, value, avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS smooth FROM events) SELECT user_id, round(var_samp(value), 4) AS token_var, round(var_samp(smooth), 4) AS rendered_var FROM m GROUP BY user_id"


@query("c14_spread", SPREAD)
def c14_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "events").select("user_id", "event_id", "value", F.col("value").alias("smooth"))
    out = reward.spread(tokens.moving(rows, "smooth", 2, "user_id", "event_id"), "user_id", "value", "smooth")
    return out.select("user_id", F.round("token_var", 4).alias("token_var"), F.round("rendered_var", 4).alias("rendered_var"))


