"""Queries: methods, measures, baselines and experiment workloads over the given tables, each with its SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import objective as O
from ..functions import prompts, responses, rewards
from ..functions.labels import NONE
from ..functions.portable import hash_hex
from ..ontology import LABELS, candidates, load_ontology, recompose
from ..operators import metrics as M
from ..operators import sampling, schedule
from ..policy import expert
from ..sources import tables as T
from ..sources.io import write_stage
from .oracle_views import BRIEF, GUIDE, HINT, LABEL_LIST, advantages, hashed, hashed_int, using

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None, *views: str):
    """Registers a query under its function's name, with its SQL over the named views."""

    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = using(*views, query=sql)
        return f

    return add


def label_array():
    return F.array(*[F.lit(x) for x in LABELS])


def joined(c):
    return F.array_join(c, ",")


# --- samples --------------------------------------------------------------------------------------------------


@query("SELECT sample_id, vec_id, x0, y0, entity, ent_type, obj_type, gold, split FROM samples", "samples")
def samples_view(spark, d):
    return T.build_samples(spark, d).select("sample_id", "vec_id", F.col("box.x0").alias("x0"), F.col("box.y0").alias("y0"), "entity", "ent_type", "obj_type", "gold", "split")


@query("SELECT sample_id, len(crop)::BIGINT AS cells, round(list_sum(crop), 6) AS total, round(crop[1], 6) AS first_cell, round(crop[16], 6) AS last_cell FROM samples", "samples")
def object_crop(spark, d):
    c = F.col("crop")
    total = F.aggregate(c, F.lit(0.0), lambda a, x: a + x)
    return T.build_samples(spark, d).select("sample_id", F.size(c).cast("long").alias("cells"), F.round(total, 6).alias("total"), F.round(F.get(c, F.lit(0)), 6).alias("first_cell"), F.round(F.get(c, F.lit(15)), 6).alias("last_cell"))


@query("""SELECT page_id, box_start, box_end, CASE WHEN box_end > box_start THEN substr(html, box_start + 1, box_end - box_start) END AS crop, len(regexp_extract_all(html, '<[a-zA-Z][^>]*>'))::BIGINT AS n_tags
  FROM (SELECT *, CASE WHEN box_start >= 0 THEN box_start + strpos(substr(html, box_start + 1), '</p>') + 3 END AS box_end FROM (SELECT *, strpos(html, '<p>') - 1 AS box_start FROM pages))""")
def region_from_page(spark, d):
    return T.page_regions(spark, d).withColumns({c: F.col(c).cast("long") for c in ("box_start", "box_end", "n_tags")})


@query("SELECT split, gold, count(*) AS n FROM samples GROUP BY split, gold", "samples")
def split_histogram(spark, d):
    return T.build_samples(spark, d).groupBy("split", "gold").agg(F.count("*").alias("n"))


@query("SELECT split, count(*) AS rows, max(n) AS largest, min(n) AS smallest, sum(n)::BIGINT AS total, round(max(n)::DOUBLE / min(n), 6) AS imbalance FROM (SELECT split, gold, count(*) AS n FROM samples GROUP BY ALL) GROUP BY split", "samples")
def class_imbalance(spark, d):
    n = split_histogram(spark, d)
    return n.groupBy("split").agg(F.count("*").alias("rows"), F.max("n").alias("largest"), F.min("n").alias("smallest"), F.sum("n").alias("total"), F.round(F.max("n") / F.min("n"), 6).alias("imbalance"))


# --- labels and prompts ---------------------------------------------------------------------------------------

_TYPES = "(SELECT unnest(['per', 'org', 'loc', 'misc']) AS t)"


_CANDIDATES = f"SELECT o.t AS obj_type, e.t AS ent_type, (SELECT count(*) FROM ontology r WHERE r.obj_type = o.t AND r.ent_type = e.t) + 1 AS n, coalesce((SELECT string_agg(label, ',' ORDER BY seq) FROM ontology r WHERE r.obj_type = o.t AND r.ent_type = e.t) || ',', '') || 'none' AS labels FROM {_TYPES} o, {_TYPES} e"


@query(f"SELECT sample_id, s.obj_type, s.ent_type, coalesce(n, 1)::BIGINT AS n, coalesce(labels, 'none') AS labels FROM samples s LEFT JOIN ({_CANDIDATES}) c ON c.obj_type = s.obj_type AND c.ent_type = s.ent_type", "samples", "ontology")
def ontology_candidates(spark, d):
    s = T.build_samples(spark, d).select("sample_id", "obj_type", "ent_type").join(F.broadcast(candidates(load_ontology(spark))), ["obj_type", "ent_type"], "left")  # 16 rows
    allowed = F.coalesce("labels", F.array(F.lit(NONE)))  # types unknown: none only
    return s.select("sample_id", "obj_type", "ent_type", F.size(allowed).cast("long").alias("n"), joined(allowed).alias("labels"))


@query("SELECT s.obj_type, s.ent_type, count(*) AS n, avg((SELECT count(*) FROM ontology r WHERE r.obj_type = s.obj_type AND r.ent_type = s.ent_type) + 1)::DOUBLE AS kept, sum((s.gold = 'none' OR s.gold LIKE '/' || s.obj_type || '/' || s.ent_type || '/%')::INT)::BIGINT AS gold_kept FROM samples s GROUP BY ALL", "samples", "ontology")
def candidate_narrowing(spark, d):
    c = candidates(load_ontology(spark))
    s = T.build_samples(spark, d).join(F.broadcast(c), ["obj_type", "ent_type"])  # 16 rows
    return s.groupBy("obj_type", "ent_type").agg(F.count("*").alias("n"), F.avg(F.size("labels").cast("double")).alias("kept"), F.sum(F.array_contains("labels", F.col("gold")).cast("long")).alias("gold_kept"))


@query("SELECT sample_id, gold AS label, gold AS again FROM samples", "samples")
def label_roundtrip(spark, d):
    return recompose(T.build_samples(spark, d).select("sample_id", F.col("gold").alias("label")))


@query(f"SELECT sample_id, md5({BRIEF}) AS prompt_md5, length({BRIEF})::BIGINT AS chars FROM samples", "samples")
def task_brief_prompt(spark, d):
    s = T.build_samples(spark, d).withColumn("prompt", prompts.task_brief(LABELS, F.col("text"), F.col("entity")))
    return s.select("sample_id", F.md5(F.col("prompt").cast("binary")).alias("prompt_md5"), F.length("prompt").cast("long").alias("chars"))


@query(f"SELECT sample_id, md5({BRIEF} || chr(10) || {GUIDE} || chr(10) || {HINT}) AS prompt_md5 FROM cold WHERE drawn", "cold")
def expert_prompt(spark, d):
    s = _cold(spark, d)[0].withColumn("prompt", prompts.expert_prompt(LABELS, F.col("text"), F.col("entity"), F.col("gold")))
    return s.select("sample_id", F.md5(F.col("prompt").cast("binary")).alias("prompt_md5"))


@query(f"SELECT sample_id, md5({BRIEF}) AS prompt_md5, false AS has_hint FROM cold WHERE drawn", "cold")
def learner_prompt(spark, d):
    s = _cold(spark, d)[0].withColumn("prompt", prompts.learner_prompt(LABELS, F.col("text"), F.col("entity")))
    return s.select("sample_id", F.md5(F.col("prompt").cast("binary")).alias("prompt_md5"), F.col("prompt").contains("Hint: ").alias("has_hint"))


# --- cold start -----------------------------------------------------------------------------------------------


def _train(spark, d):
    return T.build_samples(spark, d).where("split = 'train'")


def _cold(spark, d, **how):
    return sampling.stratified_draw(_train(spark, d), **how)


@query("SELECT sample_id, gold FROM cold WHERE drawn", "cold")
def cold_draw_exact(spark, d):
    return _cold(spark, d)[0].select("sample_id", "gold")


@query(f"SELECT sample_id, gold FROM samples WHERE split = 'train' AND {hashed(42, 'cold', 'sample_id')} < '40000000'", "samples")
def cold_draw_bernoulli(spark, d):
    return _cold(spark, d, exact=False)[0].select("sample_id", "gold")


@query("SELECT sample_id, gold FROM cold WHERE NOT drawn", "cold")
def cold_rest_antijoin(spark, d):
    return _cold(spark, d)[1].select("sample_id", "gold")


@query("SELECT (SELECT count(*) FROM cold WHERE drawn) AS drawn, (SELECT count(*) FROM cold WHERE NOT drawn) AS rest, 0::BIGINT AS both, (SELECT count(*) FROM cold) AS train", "cold")
def set_disjointness(spark, d):
    drawn, rest = (x.select("sample_id") for x in _cold(spark, d))
    n = lambda df, name: df.agg(F.count("*").alias(name))
    out = n(drawn, "drawn").crossJoin(n(rest, "rest")).crossJoin(n(drawn.intersect(rest), "both"))
    return out.crossJoin(n(drawn.union(rest).distinct(), "train"))


def _annotated(spark, d):
    return expert.annotate(_cold(spark, d)[0])


def _reasoned(spark, d):
    a = _annotated(spark, d).withColumn("x", responses.parse_response(F.col("response")))
    return a.withColumn("reason", responses.reject_reason(F.col("x"), F.col("gold"), label_array()))


@query("SELECT sample_id, gold, response FROM annotated", "annotated")
def annotate_rule_expert(spark, d):
    return _annotated(spark, d)


@query("SELECT sample_id, len(steps)::BIGINT AS n_steps, step_order, answer, coalesce(steps[1], '') AS first_step, well_formed FROM parsed_annotated", "parsed_annotated")
def parse_steps(spark, d):
    x = F.col("x")
    return _reasoned(spark, d).select("sample_id", F.size(x["steps"]).cast("long").alias("n_steps"), x["order"].alias("step_order"), x["answer"].alias("answer"), F.coalesce(F.get(x["steps"], F.lit(0)), F.lit("")).alias("first_step"), x["well_formed"].alias("well_formed"))


@query("SELECT sample_id, gold, reason FROM reasoned", "reasoned")
def annotation_filter(spark, d):
    return _reasoned(spark, d).select("sample_id", "gold", "reason")


@query("SELECT reason, count(*) AS n, sum(length(response))::BIGINT AS chars, round(count(*)::DOUBLE / (SELECT count(*) FROM reasoned), 6) AS share FROM reasoned GROUP BY reason", "reasoned")
def annotation_yield(spark, d):
    r = _reasoned(spark, d).groupBy("reason").agg(F.count("*").alias("n"), F.sum(F.length("response")).cast("long").alias("chars"))
    return r.withColumn("share", F.round(F.col("n") / F.sum("n").over(W.partitionBy()), 6))  # a row per reason


@query(f"SELECT sample_id, to_json({{'messages': [{{'role': 'user', 'content': 'Entity: ' || entity}}, {{'role': 'assistant', 'content': response}}]}})::VARCHAR AS line FROM reasoned JOIN (SELECT sample_id, entity FROM cold) USING (sample_id) WHERE reason = 'ok'", "reasoned")
def chat_export(spark, d):
    kept = _reasoned(spark, d).where("reason = 'ok'").join(_train(spark, d).select("sample_id", "entity"), "sample_id")
    turn = lambda role, c: F.struct(F.lit(role).alias("role"), c.alias("content"))
    line = F.to_json(F.struct(F.array(turn("user", F.concat(F.lit("Entity: "), "entity")), turn("assistant", F.col("response"))).alias("messages")))
    return kept.select("sample_id", line.alias("line"))


# --- rewards and the objective --------------------------------------------------------------------------------


def _rewarded(spark, d):
    g = T.logged_groups(spark, d)
    g = g.withColumn("answer", responses.parse_response(F.col("response"))["answer"])
    g = g.withColumns({"r_format": rewards.format_reward(F.col("response"), label_array()), "r_length": rewards.length_reward(F.col("response")), "r_answer": rewards.answer_reward(F.col("answer"), F.col("gold"))})
    return g.withColumn("reward", rewards.total_reward(F.col("r_format"), F.col("r_length"), F.col("r_answer")))


def _tabular(spark, d):
    return T.tabular_groups(spark, d).withColumn("reward", rewards.total_reward(F.col("r_format"), F.col("r_length"), F.col("r_answer")))


def _termed(df, ddof=0):
    df = df.withColumn("adv", O.advantage_flat("reward", ["sample_id"], ddof)).withColumn("ratio", O.policy_ratio(F.col("lp_cur"), F.col("lp_old")))
    return df.withColumns({"clipped": O.clipped_term(F.col("ratio"), F.col("adv")), "divergence": O.divergence_term(F.col("lp_cur"), F.col("lp_ref")), "is_cut": O.is_clipped(F.col("ratio"), F.col("adv"))})


def _r(c, n=6):
    return F.round(c, n).alias(c)


@query("SELECT sample_id, k, r_format FROM rewarded", "rewarded")
def format_reward(spark, d):
    return _rewarded(spark, d).select("sample_id", "k", "r_format")


@query("SELECT sample_id, k, r_length FROM rewarded", "rewarded")
def length_reward_char(spark, d):
    return _rewarded(spark, d).select("sample_id", "k", "r_length")


@query("SELECT sample_id, k, (len(regexp_extract_all(response, '\\S+')) > 100)::INT::DOUBLE AS r_length FROM logged", "logged")
def length_reward_token(spark, d):
    return T.logged_groups(spark, d).select("sample_id", "k", rewards.length_reward(F.col("response"), 100, "token").alias("r_length"))


@query("SELECT sample_id, k, answer, r_answer FROM rewarded", "rewarded")
def answer_reward(spark, d):
    return _rewarded(spark, d).select("sample_id", "k", "answer", "r_answer")


@query("SELECT sample_id, k, r_format, r_length, r_answer, reward FROM rewarded", "rewarded")
def total_reward(spark, d):
    return _rewarded(spark, d).select("sample_id", "k", "r_format", "r_length", "r_answer", "reward")


@query("SELECT sample_id, k, reward, round(adv, 6) AS adv FROM advantaged", "advantaged")
def advantage_flat(spark, d):
    return _termed(_rewarded(spark, d)).select("sample_id", "k", "reward", _r("adv"))


@query("SELECT sample_id, k, round(adv, 6) AS adv FROM advantaged", "advantaged")
def advantage_nested(spark, d):
    g = _rewarded(spark, d).groupBy("sample_id").agg(F.sort_array(F.collect_list(F.struct("k", "reward"))).alias("g"))
    g = g.withColumn("a", O.advantage_nested(F.col("g.reward")))
    return g.select("sample_id", F.explode(F.arrays_zip(F.col("g.k").alias("k"), "a")).alias("z")).select("sample_id", F.col("z.k").alias("k"), F.round("z.a", 6).alias("adv"))


@query(f"SELECT sample_id, k, round(adv, 6) AS adv FROM ({advantages('rewarded', 1)})", "rewarded")
def advantage_ddof1(spark, d):
    return _termed(_rewarded(spark, d), 1).select("sample_id", "k", _r("adv"))


@query("SELECT sample_id, k, round(ratio, 6) AS ratio FROM termed", "termed")
def ratio_terms(spark, d):
    return _termed(_rewarded(spark, d)).select("sample_id", "k", _r("ratio"))


@query("SELECT sample_id, k, round(clipped, 6) AS clipped, is_cut FROM termed", "termed")
def clipped_terms(spark, d):
    return _termed(_rewarded(spark, d)).select("sample_id", "k", _r("clipped"), "is_cut")


@query("SELECT sample_id, k, round(divergence, 6) AS divergence FROM termed", "termed")
def divergence_terms(spark, d):
    return _termed(_rewarded(spark, d)).select("sample_id", "k", _r("divergence"))


def _by_group(df, beta=0.001):
    return df.groupBy("sample_id").agg(F.count("*").alias("k"), F.round(F.avg("reward"), 6).alias("reward"), F.round(F.avg(F.col("clipped") - F.lit(beta) * F.col("divergence")), 6).alias("objective"))


_GROUP_SQL = "SELECT sample_id, count(*) AS k, round(avg(reward), 6) AS reward, round(avg(clipped - 0.001::DOUBLE * divergence), 6) AS objective FROM {} GROUP BY sample_id"


@query(_GROUP_SQL.format("termed"), "termed")
def objective_by_group(spark, d):
    return _by_group(_termed(_rewarded(spark, d)))


@query("SELECT count(*) AS groups, round(avg(o), 6) AS objective FROM (SELECT avg(clipped - 0.001::DOUBLE * divergence) AS o FROM termed GROUP BY sample_id)", "termed")
def objective_batch(spark, d):
    per = _termed(_rewarded(spark, d)).groupBy("sample_id").agg(F.avg(F.col("clipped") - 0.001 * F.col("divergence")).alias("o"))
    return per.agg(F.count("*").alias("groups"), F.round(F.avg("o"), 6).alias("objective"))


def _stats(df):
    spread = df.groupBy("sample_id").agg((F.max("reward") == F.min("reward")).cast("double").alias("flat"))
    return df.agg(F.count("*").alias("responses"), F.round(F.avg("ratio"), 6).alias("ratio"), F.round(F.avg("divergence"), 6).alias("divergence"), F.round(F.avg(F.col("is_cut").cast("double")), 6).alias("cut_share")).crossJoin(spread.agg(F.round(F.avg("flat"), 6).alias("flat_share")))  # one row each


@query("SELECT count(*) AS responses, round(avg(ratio), 6) AS ratio, round(avg(divergence), 6) AS divergence, round(avg(is_cut::INT::DOUBLE), 6) AS cut_share, (SELECT round(avg((hi = lo)::INT::DOUBLE), 6) FROM (SELECT max(reward) AS hi, min(reward) AS lo FROM termed GROUP BY sample_id)) AS flat_share FROM termed", "termed")
def update_stats(spark, d):
    return _stats(_termed(_rewarded(spark, d)))


@query("SELECT sample_id, k, reward, round(adv, 6) AS adv FROM tabular_adv", "tabular_adv")
def advantage_lineitem(spark, d):
    return _termed(_tabular(spark, d)).select("sample_id", "k", "reward", _r("adv"))


@query(_GROUP_SQL.format("tabular_terms"), "tabular_terms")
def objective_lineitem(spark, d):
    return _by_group(_termed(_tabular(spark, d)))


@query("SELECT sample_id, k, round(CASE WHEN is_cut THEN 0 ELSE ratio * adv END - 0.001::DOUBLE * (1 - exp(lp_ref - lp_cur)), 6) AS weight FROM termed", "termed")
def gradient_weights(spark, d):
    t = _termed(_rewarded(spark, d))
    return t.select("sample_id", "k", F.round(O.gradient_weight(F.col("ratio"), F.col("adv"), F.col("lp_cur"), F.col("lp_ref")), 6).alias("weight"))


@query("SELECT conv_id, turn, array_to_string((string_split(text, ' '))[1:20], ' ') AS cut FROM conversations")
def truncate_completion(spark, d):
    return T.table(spark, d, "conversations").select("conv_id", "turn", responses.truncate_tokens(F.col("text"), 20).alias("cut"))


# --- pools, schedule and batches ------------------------------------------------------------------------------


def _pools(spark, d):
    """Written once: everything after it reads ids, labels and pools only."""
    rest = _cold(spark, d)[1].select("sample_id", "gold")
    skill = F.substring(hash_hex(7, "skill", F.col("sample_id")), 1, 2)
    preds = rest.select("sample_id", F.when(skill < "ca", F.col("gold")).otherwise("no answer").alias("pred"))
    return write_stage(schedule.split_by_difficulty(rest, preds), "pools", ("pool",))


@query("SELECT sample_id, gold, pool FROM pools", "pools")
def difficulty_split(spark, d):
    return _pools(spark, d)


@query("SELECT coalesce(pool, 'all') AS pool, count(*) AS rows, sum((gold = 'none')::INT)::BIGINT AS none_rows, round(sum((gold = 'none')::INT)::DOUBLE / count(*), 6) AS none_share FROM pools GROUP BY ROLLUP (pool)", "pools")
def pool_profile(spark, d):
    return schedule.pool_profile(_pools(spark, d))


_GRID = "(SELECT *, alpha ** (t - 1) AS r FROM (SELECT o_orderdate::DATE AS day, quarter(o_orderdate)::INT AS t, count(*)::BIGINT AS batch FROM orders GROUP BY ALL), (SELECT unnest([0.25, 0.5, 1.0])::DOUBLE AS alpha))"


@query("""SELECT year, alpha, t, round(r, 6) AS ratio, easy, hard, least(easy, floor(hard * r + 0.5))::BIGINT AS drawn FROM (SELECT *, alpha ** (t - 1) AS r FROM (
  SELECT year, t, n - hard AS easy, hard FROM (SELECT year(o_orderdate)::INT AS year, quarter(o_orderdate)::INT AS t, count(*)::BIGINT AS n, coalesce(sum((substr(o_orderpriority, 1, 1) <= '2')::INT), 0)::BIGINT AS hard FROM orders GROUP BY ALL)),
  (SELECT unnest([0.25, 0.5, 1.0])::DOUBLE AS alpha))""")
def mix_ratio_table(spark, d):
    return schedule.ratio_table(T.order_pools(spark, d))


@query(f"SELECT day, batch, alpha, t, round(r, 6) AS ratio, ceil(batch * r / (1 + r) - 1e-9)::BIGINT AS easy, ceil(batch / (1 + r) - 1e-9)::BIGINT AS hard FROM {_GRID}")
def batch_quota_table(spark, d):
    return schedule.quota_table(T.order_steps(spark, d))


@query(f"SELECT day, batch, alpha, t, round(r, 6) AS ratio, batch - ceil(batch / (1 + r) - 1e-9)::BIGINT AS easy, ceil(batch / (1 + r) - 1e-9)::BIGINT AS hard FROM {_GRID}")
def batch_quota_trim(spark, d):
    return schedule.quota_table(T.order_steps(spark, d), fit="trim")


def _none_share(spark, d):
    return _train(spark, d).agg(F.avg((F.col("gold") == NONE).cast("double"))).first()[0] or 0.0  # one number


def _draw_sql(t: int, ratio: float, stream: str) -> str:
    """All hard rows and the proportional easy draw of epoch t."""
    return f"""SELECT sample_id, gold, 'hard' AS pool, {t} AS epoch FROM pools WHERE pool = 'hard' UNION ALL
      SELECT sample_id, gold, 'easy' AS pool, {t} AS epoch FROM (SELECT *, row_number() OVER (PARTITION BY gold = 'none' ORDER BY {hashed(42, stream, 'sample_id')}, sample_id) AS rn FROM pools WHERE pool = 'easy'), (
        SELECT least(hn, n - least(hr, n - n0)) AS none_n, least(hr, n - n0) AS real_n FROM (SELECT *, least(hn, floor(n * ns + 0.5)) AS n0 FROM (
          SELECT least(floor(sum((pool = 'hard')::INT) * {ratio} + 0.5), sum((pool = 'easy')::INT)) AS n, sum((pool = 'easy' AND gold = 'none')::INT) AS hn, sum((pool = 'easy' AND gold <> 'none')::INT) AS hr, (SELECT avg((gold = 'none')::INT::DOUBLE) FROM samples WHERE split = 'train') AS ns FROM pools)))
      WHERE rn <= CASE WHEN gold = 'none' THEN none_n ELSE real_n END"""


def _epoch(spark, d, t, **how):
    return schedule.epoch_pool(_pools(spark, d), t, _none_share(spark, d), **how).withColumn("epoch", F.lit(t))


@query(_draw_sql(2, 0.5, "easy2"), "pools")
def epoch_pool_progressive(spark, d):
    return _epoch(spark, d, 2)


@query(_draw_sql(2, 1.0, "easy2"), "pools")
def epoch_pool_equal(spark, d):
    return _epoch(spark, d, 2, strategy="equal")


@query("SELECT sample_id, gold, pool, 1 AS epoch FROM pools WHERE pool = 'hard'", "pools")
def epoch_pool_hard_only(spark, d):
    return _epoch(spark, d, 1, strategy="hard_only")


@query("SELECT sample_id, gold, pool, 1 AS epoch FROM pools", "pools")
def epoch_pool_raw(spark, d):
    return _epoch(spark, d, 1, strategy="raw")


@query(f"SELECT sample_id, gold FROM ({_draw_sql(1, 1.0, 'easy1')}) WHERE pool = 'easy'", "pools")
def easy_draw_proportional(spark, d):
    return _epoch(spark, d, 1).where("pool = 'easy'").select("sample_id", "gold")


@query(f"""SELECT sample_id, gold, pool, step, row_number() OVER (PARTITION BY step ORDER BY {hashed(42, 'slot2', 'sample_id')}, sample_id) - 1 AS slot FROM (
  SELECT sample_id, gold, pool, (row_number() OVER (PARTITION BY pool ORDER BY {hashed(42, 'batch2', 'sample_id')}, sample_id) - 1) // CASE pool WHEN 'easy' THEN 6 ELSE 11 END AS step FROM ({_draw_sql(2, 0.5, 'easy2')}))""", "pools")
def batch_assignment(spark, d):
    easy, hard = schedule.batch_quota(16, 2)
    return schedule.assign_batches(_epoch(spark, d, 2).drop("epoch"), easy, hard, 2)


@query("""SELECT user_id, event_id, s AS step, 0.0001::DOUBLE * least(1, (s + 1)::DOUBLE / greatest(1, floor(n * 0.05::DOUBLE))) AS lr FROM (
  SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts NULLS FIRST, event_id NULLS FIRST) - 1 AS s, count(*) OVER (PARTITION BY user_id) AS n FROM events)""")
def warmup_table(spark, d):
    """A user's events in order of time are the steps of a run."""
    of = W.partitionBy("user_id")
    s = T.table(spark, d, "events").select("user_id", "event_id", (F.row_number().over(of.orderBy("ts", "event_id")) - 1).cast("long").alias("step"), F.count("*").over(of).alias("total"))
    return s.select("user_id", "event_id", "step", schedule.warmup(F.col("step"), F.col("total"), 1e-4, 0.05).alias("lr"))


# --- measures -------------------------------------------------------------------------------------------------


def predictions(spark, d):
    """Three stand-in methods of different skill over the test split."""
    test = T.build_samples(spark, d).where("split = 'test'").select("sample_id", "gold")
    cuts = spark.createDataFrame([("strong", "d0"), ("middle", "b0"), ("weak", "90")], "method string, cut string")
    p = test.crossJoin(F.broadcast(cuts))  # three rows
    h = lambda stream: F.md5(F.concat_ws(":", F.lit("7"), F.lit(stream), "method", F.col("sample_id").cast("string")).cast("binary"))
    other = F.get(label_array(), (F.conv(F.substring(h("other"), 1, 7), 16, 10).cast("long") % len(LABELS)).cast("int"))
    return p.select("method", "sample_id", "gold", F.when(F.substring(h("pred"), 1, 2) < F.col("cut"), F.col("gold")).otherwise(other).alias("pred"))


@query("SELECT * FROM metrics", "metrics")
def accuracy_prf(spark, d):
    return M.accuracy_prf(predictions(spark, d))


_EACH = """(SELECT method, label, support, predicted, tp, coalesce(tp::DOUBLE / nullif(predicted, 0), 0) AS p, coalesce(tp::DOUBLE / nullif(support, 0), 0) AS r FROM (
  SELECT method, label, sum(g)::BIGINT AS support, sum(s)::BIGINT AS predicted, sum(t)::BIGINT AS tp FROM (SELECT method, gold AS label, 1 AS g, 0 AS s, (gold = pred)::INT AS t FROM preds UNION ALL SELECT method, pred, 0, 1, 0 FROM preds) GROUP BY ALL))"""


@query(f"SELECT method, label, support, predicted, tp, round(p, 6) AS p, round(r, 6) AS r, round(coalesce(2 * p * r / nullif(p + r, 0), 0), 6) AS f1 FROM {_EACH}", "preds")
def per_class(spark, d):
    return M.per_class(predictions(spark, d))


@query(f"SELECT method, round(avg(round(p, 6)), 5) AS p, round(avg(round(r, 6)), 5) AS r, round(avg(round(coalesce(2 * p * r / nullif(p + r, 0), 0), 6)), 5) AS f1 FROM {_EACH} WHERE support > 0 GROUP BY method", "preds")
def prf_macro(spark, d):
    return M.averaged_prf(predictions(spark, d), "macro")


@query(f"SELECT method, round(sum(round(p, 6) * support) / sum(support), 5) AS p, round(sum(round(r, 6) * support) / sum(support), 5) AS r, round(sum(round(coalesce(2 * p * r / nullif(p + r, 0), 0), 6) * support) / sum(support), 5) AS f1 FROM {_EACH} WHERE support > 0 GROUP BY method", "preds")
def prf_weighted(spark, d):
    return M.averaged_prf(predictions(spark, d), "weighted")


@query("SELECT method, round(avg((gold = pred)::INT::DOUBLE), 6) AS p, round(avg((gold = pred)::INT::DOUBLE), 6) AS r, round(avg((gold = pred)::INT::DOUBLE), 6) AS f1 FROM preds GROUP BY method", "preds")
def prf_micro_all(spark, d):
    return M.averaged_prf(predictions(spark, d), "micro")


@query("SELECT method, gold, pred, count(*) AS n FROM preds GROUP BY ALL", "preds")
def confusion_matrix(spark, d):
    return M.confusion(predictions(spark, d))


@query("SELECT method, gold, pred, n, place FROM (SELECT *, row_number() OVER (PARTITION BY method ORDER BY n DESC, gold, pred) AS place FROM (SELECT method, gold, pred, count(*) AS n FROM preds WHERE gold <> pred GROUP BY ALL)) WHERE place <= 10", "preds")
def top_confusions(spark, d):
    return M.top_confusions(predictions(spark, d))


@query("""SELECT method, tp, fp, fn, tn, round(fp::DOUBLE / nullif(fp + tn, 0), 6) AS over_rate, round((tp + tn)::DOUBLE / (tp + fp + fn + tn), 6) AS binary_acc FROM (SELECT method, sum((gold <> 'none' AND pred <> 'none')::INT)::BIGINT AS tp, sum((gold = 'none' AND pred <> 'none')::INT)::BIGINT AS fp, sum((gold <> 'none' AND pred = 'none')::INT)::BIGINT AS fn, sum((gold = 'none' AND pred = 'none')::INT)::BIGINT AS tn FROM preds GROUP BY method)""", "preds")
def none_discrimination(spark, d):
    return M.none_discrimination(predictions(spark, d))


_SAME_TYPES = "(split_part(gold, '/', 2) = split_part(pred, '/', 2))::INT::DOUBLE AS o, (split_part(gold, '/', 3) = split_part(pred, '/', 3))::INT::DOUBLE AS e"


@query(f"SELECT method, count(*) AS n, round(avg(o), 6) AS obj_acc, round(avg(e), 6) AS ent_acc, round(avg(o * e), 6) AS both_acc FROM (SELECT method, {_SAME_TYPES} FROM preds WHERE gold <> 'none' AND pred <> 'none') GROUP BY method", "preds")
def type_accuracy(spark, d):
    return M.type_accuracy(predictions(spark, d))


@query("SELECT metric, round(max(value) FILTER (method = 'strong') / max(value) FILTER (method = 'middle') - 1, 6) AS gain FROM (UNPIVOT metrics ON acc, p, r, f1 INTO NAME metric VALUE value) GROUP BY metric", "metrics")
def relative_gain(spark, d):
    return M.relative_gain(M.accuracy_prf(predictions(spark, d)), "strong", "middle")


@query("SELECT method, metric, value, dense_rank() OVER (PARTITION BY metric ORDER BY value DESC) AS place FROM (UNPIVOT metrics ON acc, p, r, f1 INTO NAME metric VALUE value)", "metrics")
def rank_methods(spark, d):
    return M.rank_methods(M.accuracy_prf(predictions(spark, d)))


_T = "coalesce(split_part({0}, '/', 2) = split_part(gold, '/', 2) AND split_part({0}, '/', 3) = split_part(gold, '/', 3), false) AS types_{1}"


@query(f"""SELECT sample_id, gold, a AS said_weak, {_T.format('a', 'weak')}, b AS said_middle, {_T.format('b', 'middle')}, c AS said_strong, {_T.format('c', 'strong')} FROM (
  SELECT sample_id, gold, max(pred) FILTER (method = 'weak') AS a, max(pred) FILTER (method = 'middle') AS b, max(pred) FILTER (method = 'strong') AS c FROM preds GROUP BY ALL) WHERE c = gold AND a <> gold AND b <> gold""", "preds")
def case_study(spark, d):
    return M.case_study(predictions(spark, d), ["weak", "middle", "strong"])


_EDGES = "(SELECT vec_id AS head, split_part(pred, '/', 4) AS relation, entity AS tail, count(*) AS n FROM preds JOIN (SELECT sample_id, vec_id, entity FROM samples) USING (sample_id) WHERE pred <> 'none' AND method = 'strong' GROUP BY ALL)"


@query(f"SELECT * FROM {_EDGES}", "preds", "samples")
def edge_export(spark, d):
    return M.to_edges(T.build_samples(spark, d), predictions(spark, d).where("method = 'strong'"))


@query(f"SELECT * FROM {_EDGES} WHERE relation = 'member_of'", "preds", "samples")
def relation_lookup(spark, d):
    return M.lookup(edge_export(spark, d), "member_of")


# --- baselines without training -------------------------------------------------------------------------------


def _test(spark, d):
    return T.build_samples(spark, d).where("split = 'test'")


@query(f"SELECT sample_id, gold, {LABEL_LIST}[{hashed_int(7, 'uniform', 'sample_id')} % {len(LABELS)} + 1] AS pred FROM samples WHERE split = 'test'", "samples")
def zero_shot_uniform(spark, d):
    return expert.zero_shot_uniform(_test(spark, d))


@query("SELECT sample_id, gold, coalesce((SELECT min_by(label, seq) FROM ontology o WHERE o.obj_type = s.obj_type AND o.ent_type = s.ent_type), 'none') AS pred FROM samples s WHERE split = 'test'", "samples", "ontology")
def zero_shot_prior(spark, d):
    return expert.zero_shot_prior(_test(spark, d), load_ontology(spark))


@query("SELECT sample_id, gold, (SELECT gold FROM samples WHERE split = 'train' GROUP BY gold ORDER BY count(*) DESC, gold DESC LIMIT 1) AS pred FROM samples WHERE split = 'test'", "samples")
def majority_floor(spark, d):
    return expert.majority(_train(spark, d), _test(spark, d))
